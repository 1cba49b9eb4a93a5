"""What the operators share: table access, the shared folder, Arrow mapping, per-process caches."""

import ctypes
import gc
import sys
import uuid

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def shared_folder(spark: SparkSession, what: str) -> str:
    """A new folder below the checkpoint folder that the cluster names; all executors see it.

    Only where the session names none (tests on one machine) the working directory's warehouse serves.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base is None:
        set_dir = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = set_dir.get() if set_dir.isDefined() else None
    if base is None:
        base = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_scratch"
    return f"{base.rstrip('/')}/graftmill-{what}-{uuid.uuid4().hex}"


def stored(df: DataFrame, what: str) -> DataFrame:
    """Write and read again: cuts the lineage at files every executor can read."""
    path = shared_folder(df.sparkSession, what)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


#: Keys that a join without exchange takes at most.
HEAVY_KEYS = 100_000


def met(left: DataFrame, right: DataFrame, on: list[str], rows: str, total: int, floor: int) -> DataFrame:
    """The inner join of left with right, which holds each key once, with the number of its rows in left in the column ``rows``.

    Keys with more than floor rows, and more than a HEAVY_KEYS-th of all ``total`` rows of left, of which there are fewer than HEAVY_KEYS, are broadcast; so no
    task of the exchange gets the rows of a heavy key. The column ``rows`` stays.
    """
    bar = max(floor, total // HEAVY_KEYS)
    heavy = F.broadcast(right.filter(F.col(rows) > bar))
    light = left.join(F.broadcast(right.filter(F.col(rows) > bar).select(*on)), on, "left_anti").join(right.filter(F.col(rows) <= bar), on)
    return left.join(heavy, on).unionByName(light)


def spare(df: DataFrame, name: str) -> str:
    """A column name that df does not have, in any case of letters."""
    taken = {c.lower() for c in df.columns}
    name = f"__{name}"
    while name in taken or f"{name}2" in taken:
        name += "_"
    return name


def prefix(df: DataFrame) -> str:
    """How no column of df begins."""
    out = "__"
    while any(c.startswith(out) for c in df.columns):
        out += "_"
    return out


def release(spark: SparkSession) -> None:
    """Let Spark drop the shuffle files of steps that no frame refers to any more; else they stay until the driver happens to collect its garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def drop_stored(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


#: Caches of which a worker process keeps the last used one only, so that operators that follow each other do not add up.
LARGE_CACHES = frozenset({"words", "chunks", "letters", "powers"})


def process_cache(name: str) -> dict:
    """A dict that lives as long as the worker process (pickling by value makes module globals per task)."""
    caches = sys.__dict__.setdefault("_graftmill_cache", {})
    if name in LARGE_CACHES and name not in caches:
        others = LARGE_CACHES & caches.keys()
        for other in others:
            caches.pop(other).clear()
        if others:
            tidy()
    return caches.setdefault(name, {})


def tidy() -> None:
    """Give freed memory back to the system, so that a worker that waits or goes on with something else does not hold the peak of its last batch."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # where the C library has it
    if trim is not None:
        trim(0)


def arrow_map(df: DataFrame, per_batch, schema: str, rows: int | None = None) -> DataFrame:
    """mapInArrow with a function from a RecordBatch (of at most ``rows`` rows) to a dict of columns (or None)."""
    from pyspark.sql.types import StructType
    from pyspark.sql.pandas.types import to_arrow_schema

    arrow = to_arrow_schema(StructType.fromDDL(schema))

    def run(batches):
        for batch in batches:
            if batch.num_rows == 0:
                continue
            for at in range(0, batch.num_rows, rows or batch.num_rows):
                yield from pieces(per_batch(batch.slice(at, rows)))
            tidy()

    def pieces(made):
        if made is None:
            return
        for one in made if isinstance(made, list) else [made]:
            yield pa.RecordBatch.from_arrays([pa.array(one[f.name], f.type) for f in arrow], schema=arrow)

    return df.mapInArrow(run, schema)


def texts_of(batch: pa.RecordBatch, name: str = "text") -> list:
    return batch.column(batch.schema.get_field_index(name)).to_pylist()


def column_of(batch: pa.RecordBatch, name: str):
    return batch.column(batch.schema.get_field_index(name))
