"""All registered queries and their SQL."""

from __future__ import annotations

from .plans import methods, streams, surface

QUERIES = {**methods.QUERIES, **surface.QUERIES, **streams.QUERIES}
ORACLES = {**methods.ORACLES, **surface.ORACLES, **streams.ORACLES}
