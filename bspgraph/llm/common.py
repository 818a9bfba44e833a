"""Helpers shared by the training-data operators."""

from __future__ import annotations

import ctypes
import gc
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Observation, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..plans import checkpoints
from ..plans.checkpoints import shared_folder
from ..shipping import ship

#: Most rows (a few numbers each) of a side that is broadcast; a larger side is joined by shuffle.
BROADCAST_ROWS = 100_000

#: Rows that a kernel takes at once: bounds the memory of a worker.
SLICE_ROWS = 1000

#: Ranges of a hash by which drawn rows are counted.
RANGES = 256

WORD = r"[^\x20\x09-\x0D]+"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet")


def checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder that the session names in ``spark.checkpoint.dir``; only
    where none is named and all runs in one process a temporary one is set."""
    return shared_folder(spark)


def cut(df: DataFrame) -> DataFrame:
    """Write ``df`` to the shared checkpoint folder and read it from there."""
    checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def counted(df: DataFrame, *more: Column) -> tuple[DataFrame, dict]:
    """``df`` cut, and its number of ``rows`` with ``more`` aggregates by name, seen
    by the job that writes it: a count of its own would be one more job, whose
    plan and tasks the driver keeps.  In loops, sizes guessed for the plans before
    are not handed on."""
    seen = Observation()
    out = checkpoints.cut(df.observe(seen, F.count(F.lit(1)).alias("rows"), *more))
    return out, seen.get


def small_cut(df: DataFrame) -> DataFrame:
    """``df`` cut, with a broadcast hint if its rows are few."""
    out, seen = counted(df)
    return small(out, seen["rows"])


def small(df: DataFrame, rows: int, most: int = BROADCAST_ROWS) -> DataFrame:
    """A broadcast hint if the counted ``rows`` are few, else ``df`` itself."""
    return F.broadcast(df) if rows <= most else df


def fresh(df: DataFrame, *names: str) -> list[str]:
    """The names, with marks added to those that ``df`` has a column of."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        out.append(name)
    return out


def crc_mod(doc_id: Column, modulus: int) -> Column:
    """crc32 of the identifier's decimal text, modulo ``modulus``."""
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(modulus))


def held_out(doc_id: Column, modulus: int, remainder: int) -> Column:
    """Whether the identifier falls in the held-out fold; null ids do not."""
    return F.coalesce(crc_mod(doc_id, modulus) == remainder, F.lit(False))


def map_rows(df: DataFrame, kernel: Callable[[pa.RecordBatch], dict], schema: str | StructType, at_once: int = SLICE_ROWS) -> DataFrame:
    """Apply ``kernel`` (a batch to a dict of columns) to ``at_once`` rows at a time."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    ship(df.sparkSession)
    arrow = to_arrow_schema(_parse_datatype_string(schema) if isinstance(schema, str) else schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in (b.slice(at, at_once) for b in batches for at in range(0, b.num_rows, at_once)):
            columns = kernel(part)
            yield pa.RecordBatch.from_arrays([pa.array(columns[f.name], type=f.type) for f in arrow], schema=arrow)

    mapped = df.mapInArrow(run, schema)
    mapped.made_of = df, run
    return mapped


def map_mapped(df: DataFrame, kernel: Callable[[pa.RecordBatch], dict], schema: str | StructType) -> DataFrame:
    """``map_rows`` over a frame that ``map_rows`` returned, slice by slice in the same
    worker: its rows do not go to the JVM and into a second worker between."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    source, first = df.made_of
    arrow = to_arrow_schema(_parse_datatype_string(schema) if isinstance(schema, str) else schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in first(batches):
            columns = kernel(part)
            yield pa.RecordBatch.from_arrays([pa.array(columns[f.name], type=f.type) for f in arrow], schema=arrow)

    return source.mapInArrow(run, schema)


def bounded_sample(labelled: DataFrame, keys: list[str], most: int) -> DataFrame:
    """At most ``most`` doc_ids of ``labelled(doc_id, *keys)`` per distinct key,
    one row each, however often a doc_id occurs (the least keys of one count).

    Ids are drawn by a hash against a fraction a little above the need.  Counts of
    the drawn by ranges of the hash, a bounded number, tell up to which range
    ``most`` are not exceeded.  So the same ids are chosen in every run and order,
    and no task gathers a key's rows.  Keys are class labels.
    """
    counts = cut(labelled.groupBy(*keys).agg(F.count(F.lit(1)).alias("n_of_key")))
    share = F.least(F.lit(1.0), F.lit(1.2 * most + 50) / F.col("n_of_key"))
    unit = F.pmod(F.xxhash64(F.lit("sample"), F.col("doc_id")), F.lit(1 << 30)) / F.lit(float(1 << 30))
    drawn = labelled.join(small(counts, counts.count()), keys).where(unit < share)
    drawn = drawn.withColumn("of_hash", F.floor(unit / share * RANGES).cast("int"))
    drawn = drawn.groupBy("doc_id").agg(F.min(F.struct(*keys, "of_hash")).alias("of")).select("doc_id", "of.*")
    drawn = cut(drawn)
    sizes = cut(drawn.groupBy(*keys, "of_hash").agg(F.count(F.lit(1)).alias("n")))  # keys times RANGES at most
    so_far = F.sum("n").over(Window.partitionBy(*keys).orderBy("of_hash").rowsBetween(Window.unboundedPreceding, 0))
    kept = sizes.withColumn("n", so_far).where(F.col("n") <= most).select(*keys, "of_hash")
    return cut(drawn.join(small(kept, sizes.count()), [*keys, "of_hash"], "left_semi").select("doc_id", *keys))


def sampled_texts(docs: DataFrame, chosen: DataFrame, on: list[str]) -> DataFrame:
    """The columns of ``chosen`` and one whole ``text`` for each of its doc_ids
    that ``docs`` has (the least, if rows share the id): no more rows than ids."""
    columns = chosen.columns
    rows = docs.select(*on, "text").join(small(chosen, chosen.count()), on)
    return rows.groupBy(*columns).agg(F.min("text").alias("text")).select(*columns, "text")


def release() -> None:
    """Give freed memory back to the system, where the allocator can."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


class Shared:
    """A value sent to the workers once; each worker builds its tool from it once."""

    _built: dict = {}

    def __init__(self, spark: SparkSession, value, build: Callable = lambda x: x):
        self._key, self._value, self._build = uuid.uuid4().hex, spark.sparkContext.broadcast(value), build

    def get(self):
        if self._key not in Shared._built:
            Shared._built.clear()  # the tools of earlier jobs are not needed again
            release()
            Shared._built[self._key] = self._build(self._value.value)
        return Shared._built[self._key]


def map_batches(df: DataFrame, kernel: Callable[[Iterator[pa.RecordBatch]], Iterator[dict]], schema: str) -> DataFrame:
    """Apply ``kernel`` to all batches of a partition; it yields dicts of columns."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    ship(df.sparkSession)
    arrow = to_arrow_schema(_parse_datatype_string(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for columns in kernel(batches):
            if columns:
                yield pa.RecordBatch.from_arrays([pa.array(columns[f.name], type=f.type) for f in arrow], schema=arrow)

    return df.mapInArrow(run, schema)
