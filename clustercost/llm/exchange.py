"""Small helpers shared by the operators: checkpoints, lean Arrow stages, row keys, fixed-size filters."""

from __future__ import annotations

import ctypes
import tempfile
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..filters import HashFilter, U, hash_filter  # noqa: F401

BATCH_BYTES = 8 << 20
_BATCH_LIMIT = "spark.sql.execution.arrow.maxBytesPerBatch"

Batches = Iterator[pa.RecordBatch]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def checkpointed(df: DataFrame) -> DataFrame:
    """``df.checkpoint()`` in the shared folder that the session names; a temporary one only in local mode, where none is set."""
    sc = df.sparkSession.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        folder = df.sparkSession.conf.get("spark.checkpoint.dir", None)
        if not folder:
            if not sc.master.split("[")[0] == "local":
                raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
            folder = tempfile.mkdtemp(prefix="checkpoints-")
        sc.setCheckpointDir(folder)
    return df.checkpoint()


def give_back() -> None:
    """Return freed memory to the system; a reused worker otherwise keeps its largest batch's."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc has it
    if trim is not None:
        trim(0)


def arrow_map(df: DataFrame, run: Callable[[Batches], Batches], schema: object) -> DataFrame:
    """``df.mapInArrow`` over batches of a few MB, whose memory goes back to the system after each.

    The session's limit on a batch's bytes is lowered to ``BATCH_BYTES`` where it is higher:
    whole texts come in batches of 10,000 rows otherwise, whatever their length.
    """
    conf = df.sparkSession.conf
    limit = int(str(conf.get(_BATCH_LIMIT)).rstrip("bB") or 0)
    if limit <= 0 or limit > BATCH_BYTES:
        conf.set(_BATCH_LIMIT, str(BATCH_BYTES))

    def lean(batches: Batches) -> Batches:
        def read() -> Batches:
            for batch in batches:
                yield batch
                del batch
                give_back()

        yield from run(read())
        give_back()

    return df.mapInArrow(lean, schema)


def partitions_for(spark: SparkSession, rows: int, most_rows: int = 1_000_000) -> int:
    """The session's number of shuffle partitions, or more where a partition would hold over ``most_rows``."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-rows // most_rows))


def row_key(doc_id: str = "doc_id", text: str = "text") -> Column:
    """Tells rows with one doc_id and different texts apart."""
    return F.xxhash64(F.col(doc_id), F.col(text))


def fresh(names: list[str], wanted: str) -> str:
    """``wanted``, or a longer name that no column of ``names`` has (Spark does not tell cases apart)."""
    taken = {n.lower() for n in names}
    while wanted.lower() in taken:
        wanted += "_"
    return wanted
