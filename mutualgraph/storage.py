"""Shared storage, code shipping to workers, and joins behind a size check."""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_shipped: set[str] = set()
_own_dir: dict[str, str] = {}
_stored: list[tuple[SparkSession, str]] = []

#: Bytes of rows that go to a Python worker at once, where the session leaves that open: whole texts make large rows.
BATCH_BYTES = 4 << 20
_BATCH = "spark.sql.execution.arrow.maxBytesPerBatch"


def ship(spark: SparkSession) -> None:
    """Make this package importable in Python workers, wherever they run, and keep the batches they get small."""
    if spark.conf.get(_BATCH, None) is None:
        spark.conf.set(_BATCH, str(BATCH_BYTES))
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    root = Path(__file__).resolve().parents[0]
    fd, path = tempfile.mkstemp(prefix="mutualgraph-", suffix=".zip")
    os.close(fd)
    with zipfile.ZipFile(path, "w") as z:
        for f in sorted(root.rglob("*.py")):
            z.write(f, f.relative_to(root.parent))
    spark.sparkContext.addPyFile(path)
    _shipped.add(app)


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors and the driver share: spark.checkpoint.dir, or, in local mode only, one of our own."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    app = spark.sparkContext.applicationId
    if app not in _own_dir:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        _own_dir[app] = "file://" + tempfile.mkdtemp(prefix="mutualgraph-shared-")
    return _own_dir[app]


def new_path(spark: SparkSession, label: str) -> str:
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    _stored.append((spark, path))
    return path


#: Options of tables whose rows take megabytes: a reader holds a group of rows at once.
LARGE_ROWS = {"parquet.block.size": 8 << 20, "parquet.page.size.row.check.min": 1}


def store(df: DataFrame, label: str, large_rows: bool = False) -> DataFrame:
    """Write df as Parquet in the shared folder and read it again: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = new_path(spark, label)
    df.write.options(compression="zstd", **(LARGE_ROWS if large_rows else {})).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_stored(df: DataFrame) -> None:
    """Delete a table that store() wrote; nothing may read it afterwards."""
    files = df.inputFiles()
    for spark, path in list(_stored):
        if files and f"/{path.rsplit('/', 1)[1]}/" in files[0]:
            _delete(spark, path)
            _stored.remove((spark, path))


class Passing:
    """Stored tables of which the two newest are kept: what a product wrote is dropped when the product after the next begins."""

    def __init__(self):
        self.tables: list[DataFrame] = []

    def keep(self, df: DataFrame) -> DataFrame:
        self.tables.append(df)
        while len(self.tables) > 2:
            drop_stored(self.tables.pop(0))
        return df


def free(spark: SparkSession) -> None:
    """Delete shuffle files that nothing can read any more. Spark does so when the driver's JVM collects its garbage, which
    long loops over small plans hardly bring about."""
    spark._jvm.System.gc()


def _delete(spark: SparkSession, path: str) -> None:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


@atexit.register
def _clean() -> None:
    for spark, path in _stored:
        try:
            _delete(spark, path)
        except Exception:  # noqa: BLE001  the session may be gone at exit
            return


#: Bytes of rows that may be broadcast, about (a hashed copy takes a few times that on the driver and each executor).
BROADCAST_BYTES = 16 << 20
_WIDTHS = {"boolean": 1, "string": 48, "binary": 64}


def row_bytes(df: DataFrame) -> int:
    """About what a row takes: eight bytes a number, and a guess for what varies."""
    return 16 + sum(_WIDTHS.get(kind, 1024 if kind[:5] in ("array", "struc", "map<s") else 8) for _, kind in df.dtypes)


def join_small(big: DataFrame, small: DataFrame, cond, how: str, rows: int, limit: int = 1_000_000) -> DataFrame:
    """Broadcast `small` only when its counted rows are at most `limit` and take BROADCAST_BYTES at most; otherwise
    Spark's shuffled, skew-split join."""
    fits = rows <= limit and rows * row_bytes(small) <= BROADCAST_BYTES
    return big.join(F.broadcast(small) if fits else small.hint("merge"), cond, how)
