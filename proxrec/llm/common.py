"""Helpers shared by the training-data operators: loading, text batches, shared checkpoints."""

from __future__ import annotations

import ctypes
import tempfile
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Text handled at once by a Python worker, in characters; bounds its memory whatever the batch size.
SLICE_CHARS = 2_000_000
ARROW_ROWS = 500
#: A key with fewer rows is never hot.
LEAST_HOT = 1_000
ASCII_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
ASCII_LOWER = ASCII_UPPER.lower()
#: For str.translate: A-Z only, other letters stay.
LOWER_TABLE = {ord(a): b for a, b in zip(ASCII_UPPER, ASCII_LOWER, strict=True)}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def lower_ascii(text: str) -> str:
    """Lower-cases A-Z alone, unlike str.lower()."""
    return text.lower() if text.isascii() else text.translate(LOWER_TABLE)


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Uses the cluster's shared folder; where none is named, a local session gets a temporary one and a cluster an error."""
    if spark.sparkContext.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if folder is None and not spark.sparkContext.master.startswith("local"):
            raise ValueError("name a folder that all executors share in spark.checkpoint.dir")
        spark.sparkContext.setCheckpointDir(folder or tempfile.mkdtemp(prefix="proxrec-"))


def cut(df: DataFrame) -> DataFrame:
    """Materialises df in the shared checkpoint folder, so that later reads survive lost executors."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def spread_join(rows: DataFrame, table: DataFrame, key: str, sizes: DataFrame, how: str = "inner") -> DataFrame:
    """rows joined with table, which has one row a key, so that no task gets all rows of a hot key.

    sizes(key, n) tells the rows of each key. Those above a quarter of a task's fair share (and LEAST_HOT) are hot: there are at most four times as
    many as shuffle partitions, which bounds the broadcast that names them. Their rows are dealt to as many salts as it takes, and their
    rows of the table are repeated for each.
    """
    spark = rows.sparkSession
    total, largest = sizes.agg(F.sum("n"), F.max("n")).first()
    limit = max(LEAST_HOT, (total or 0) // (4 * int(spark.conf.get("spark.sql.shuffle.partitions"))))
    if (largest or 0) <= limit:
        return rows.join(table, key, how)
    hot = [tuple(r) for r in sizes.where(F.col("n") > limit).select(key, F.ceil(F.col("n") / limit).alias("_salts")).collect()]
    named = F.broadcast(spark.createDataFrame(hot, T.StructType([T.StructField(key, table.schema[key].dataType), T.StructField("_salts", T.LongType())])))
    salts = F.coalesce("_salts", F.lit(1))
    dealt = rows.join(named, key, "left").withColumn("_salt", F.pmod(F.monotonically_increasing_id(), salts)).drop("_salts")
    repeated = table.join(named, key, "left").withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), salts - 1))).drop("_salts")
    return dealt.join(repeated, [key, "_salt"], how).drop("_salt")


def slices(batch: pa.RecordBatch, text_col: str) -> Iterator[pa.RecordBatch]:
    """Consecutive parts of a batch with at most SLICE_CHARS bytes of text, or a single row."""
    n = batch.num_rows
    if not n:
        return
    lengths = np.asarray(pc.binary_length(batch.column(text_col)).fill_null(0).to_numpy(zero_copy_only=False), dtype=np.int64)
    part = (np.cumsum(lengths) - lengths) // SLICE_CHARS
    cuts = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), n]
    for a, b in zip(cuts, cuts[1:], strict=False):
        yield batch.slice(a, b - a)


_RESIDENT: dict[object, object] = {}


def resident(key: object, build: Callable[[], object]) -> object:
    """An object that a Python worker keeps from task to task; only the latest is kept."""
    if key not in _RESIDENT:
        _RESIDENT.clear()
        _RESIDENT[key] = build()
    return _RESIDENT[key]


def give_back() -> None:
    """Returns a Python worker's unused memory to the system, for workers live on between tasks."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def small_batches(spark: SparkSession) -> None:
    """Whole texts travel to Python in batches of few rows, so that buffers on both sides stay small."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key)) <= ARROW_ROWS:
        spark.conf.set(key, str(ARROW_ROWS))


def map_text(df: DataFrame, make: Callable[[], Callable[[list], list]], fields: list[T.StructField], text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Adds columns computed from whole texts in Arrow batches.

    ``make`` runs once a task and returns a function from a list of texts (None where null) to one Arrow array (or list) a field.
    ``keep`` names the input columns that pass through (all by default). An input column named as a new one is replaced.
    """
    names = {f.name.lower() for f in fields}
    kept = [c for c in (df.columns if keep is None else keep) if c.lower() not in names]
    small_batches(df.sparkSession)
    # a text that passes through is sent once
    own = text_col in kept and isinstance(df.schema[text_col].dataType, T.StringType)
    read = text_col if own else "_llm_text"
    source = df.select(*[F.col(f"`{c}`") for c in kept], *([] if own else [F.col(f"`{text_col}`").cast("string").alias(read)]))
    schema = T.StructType([source.schema[c] for c in kept] + fields)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark.sql.pandas.types import to_arrow_schema

        if not getattr(make, "stays", False):
            _RESIDENT.clear()
        work, out = make(), to_arrow_schema(schema)
        for batch in batches:
            for part in slices(batch, read):
                made = work(part.column(read).to_pylist())
                fresh = [m if isinstance(m, pa.Array) else pa.array(m, type=out.field(len(kept) + i).type) for i, m in enumerate(made)]
                columns = [part.column(i).cast(out.field(i).type) for i in range(len(kept))] + fresh
                yield pa.RecordBatch.from_arrays(columns, schema=out)
        del work
        give_back()

    return source.mapInArrow(run, schema)


def field(name: str, kind: T.DataType) -> T.StructField:
    return T.StructField(name, kind, True)


def crc_bucket(column: str, modulus: int):
    """crc32 of the column's decimal text, modulo modulus; null ids count as the empty text."""
    return F.pmod(F.crc32(F.coalesce(F.col(column).cast("string"), F.lit("")).cast("binary")), F.lit(modulus))


def is_persisted(df: DataFrame) -> bool:
    return df.storageLevel != StorageLevel.NONE
