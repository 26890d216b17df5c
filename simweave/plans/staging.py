"""Written intermediate tables, and broadcasts behind a checked size.

Lineage is cut by writing Parquet under ``spark.checkpoint.dir``, a folder that all executors share.
Unlike a local checkpoint, a staged table outlives the executors that wrote it; unlike
``DataFrame.checkpoint()``, it is columnar, so later reads prune columns.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import threading
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A side is broadcast only if its counted rows times the row width stay below this.
BROADCAST_BYTES = 32 << 20

_RUN = uuid.uuid4().hex[:12]
_CLEANED: list[bool] = []
_OWN = threading.local()


def _scratch() -> list[dict[str, SparkSession]]:
    """Tables staged inside this thread's open scratch() blocks, by block."""
    if not hasattr(_OWN, "blocks"):
        _OWN.blocks = []
    return _OWN.blocks


def shared_dir(spark: SparkSession) -> str:
    """The folder for staged tables: spark.checkpoint.dir, or a temporary one where that is unset (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        root = f"{tempfile.gettempdir()}/simweave-staged"
        if not _CLEANED:
            _CLEANED.append(True)
            atexit.register(shutil.rmtree, f"{root}/simweave-{_RUN}", ignore_errors=True)
    return f"{root.rstrip('/')}/simweave-{_RUN}"


def stage(df: DataFrame, name: str) -> DataFrame:
    """Write df once and read it back: its plan runs a single time, and lost executors cost no recomputation."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex[:10]}"
    df.write.mode("errorifexists").option("compression", "zstd").parquet(path)
    if _scratch():
        _scratch()[-1][path] = spark
    read = spark.read.schema(df.schema).parquet(path)
    read.staged_at = path
    return read


def _delete(spark: SparkSession, where: str) -> None:
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(where)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def release(*frames: DataFrame) -> None:
    """Delete the tables of frames that stage() returned and that nothing will read again."""
    for df in frames:
        _delete(df.sparkSession, df.staged_at)
        for block in _scratch():
            block.pop(df.staged_at, None)


@contextmanager
def scratch(always: bool = False) -> Iterator[None]:
    """On a clean end (or always), delete what this thread staged inside the block; keep() a frame that is read later."""
    _scratch().append({})
    clean = False
    try:
        yield
        clean = True
    finally:
        block = _scratch().pop()
        for path, spark in block.items() if clean or always else ():
            _delete(spark, path)


def keep(df: DataFrame) -> DataFrame:
    """A staged frame that outlives the scratch() block around it."""
    blocks = _scratch()
    own = blocks[-1].pop(df.staged_at, None) if blocks else None
    if own is not None and len(blocks) > 1:
        blocks[-2][df.staged_at] = own
    return df


def drop_staged(spark: SparkSession) -> None:
    """Delete everything that this process has staged; frames that still read it become unusable."""
    _delete(spark, shared_dir(spark))


def fits_broadcast(df: DataFrame, row_bytes: int, limit: int = BROADCAST_BYTES) -> bool:
    """Whether df, a staged or cheap table, has few enough rows of at most row_bytes each."""
    most = limit // max(1, row_bytes)
    return df.limit(most + 1).agg(F.count(F.lit(1))).first()[0] <= most


def broadcast_if_small(df: DataFrame, row_bytes: int, limit: int = BROADCAST_BYTES) -> DataFrame:
    """df with a broadcast hint if its size is proven small, else as it is for a shuffled join."""
    return F.broadcast(df) if fits_broadcast(df, row_bytes, limit) else df
