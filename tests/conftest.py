import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parent.parent))

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    from clustercost.session import local_session

    return local_session(8)


@pytest.fixture(scope="session")
def sf():
    return SF
