"""Helpers shared by the corpus operators: whole-text word counts, label
folds, and tables written once to the folder that the cluster shares."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from functools import reduce
from typing import Any

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word is a run of characters other than space and the five ASCII control white spaces.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
#: Most 64-bit words of a sieve: what it broadcasts is bounded, whatever the number of keys.
SIEVE_WORDS = 1 << 20
#: Rows of an Arrow batch where whole texts or sets go to Python and the result is written at once.
TEXT_ROWS = 256
_WORKER: dict[str, Any] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def word_count(text: Column) -> Column:
    """Number of words of the whole text; 0 for null and for empty texts."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD_PATTERN)), F.lit(0)).cast("long")


def fold(doc_id: Column, folds: int) -> Column:
    """crc32 of the id written as text, modulo ``folds``; null ids fall in no fold (null)."""
    return F.crc32(doc_id.cast("string").cast("binary")) % folds


def uniform(*cols: Column, salt: str = "") -> Column:
    """A reproducible number in [0, 1) from the first 12 hex digits of an md5."""
    text = F.concat_ws("|", *[F.coalesce(c.cast("string"), F.lit("")) for c in cols], F.lit(salt))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 12), 16, 10).cast("double") / F.lit(float(1 << 48))


def shared_dir(spark: SparkSession) -> str:
    """The folder named in spark.checkpoint.dir; in local mode, where driver and executors are one process, a temporary one."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if named:
        return named.rstrip("/")
    master = spark.sparkContext.master
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    made = tempfile.mkdtemp(prefix="harvestgrid-")
    spark.sparkContext.setCheckpointDir(made)
    return spark.sparkContext.getCheckpointDir().rstrip("/")


@contextmanager
def arrow_rows(spark: SparkSession, rows: int | None) -> Iterator[None]:
    """What runs inside gets Arrow batches of at most ``rows`` rows; the session's own setting holds again afterwards."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    own = spark.conf.get(name)
    if rows is None or 0 < int(own) <= rows:
        yield
        return
    spark.conf.set(name, str(rows))
    try:
        yield
    finally:
        spark.conf.set(name, own)


def worker_table(owner: str, make: Callable[[], Any]) -> Any:
    """What a Python worker keeps between tasks for ``owner``, made at first use; the worker drops what it kept for another."""
    if owner not in _WORKER:
        _WORKER.clear()
        _WORKER[owner] = make()
    return _WORKER[owner]


def spool(df: DataFrame, tag: str = "t", codec: str = "zstd", rows: int | None = None) -> DataFrame:
    """Write ``df`` once under the shared folder and return a scan of it.

    Cuts the lineage as checkpoint() does, survives lost executors, keeps
    columnar statistics (so that small tables are broadcast only after their
    size is known) and evaluates the plan exactly once. ``rows`` bounds the Arrow batches meanwhile.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    with arrow_rows(spark, rows):
        df.write.option("compression", codec).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def sieve(keys: DataFrame) -> Callable[..., DataFrame]:
    """A Bloom filter of the one column of ``keys`` (a written table): four bits in one 64-bit word per key.

    The function returned takes (rows, key, how): left_semi gives the rows whose key may be among ``keys``, left_anti
    those whose key isn't. No row of ``keys`` is lost; of others about 1 in 100 passes, more only beyond four keys a
    word of ``SIEVE_WORDS``, so an exact join follows where it matters. The rows aren't shuffled.
    """
    words = min(SIEVE_WORDS, 1 << max(6, (keys.count() // 4).bit_length()))

    def place(key: Column) -> tuple[Column, Column]:
        h = F.xxhash64(key)
        bits = [F.call_function("shiftleft", F.lit(1).cast("long"), F.shiftrightunsigned(h, 6 * k).bitwiseAND(F.lit(63)).cast("int")) for k in range(4)]
        return F.shiftrightunsigned(h, 24).bitwiseAND(F.lit(words - 1)), reduce(Column.bitwiseOR, bits)

    at, mask = place(F.col(keys.columns[0]))
    placed = keys.select(at.cast("long").alias("sieve_word"), mask.alias("mask"))
    made = spool(placed.groupBy("sieve_word").agg(F.bit_or("mask").alias("sieve_bits")), "sieve")

    def passed(rows: DataFrame, key: Column, how: str = "left_semi") -> DataFrame:
        at, mask = place(key)
        return rows.join(F.broadcast(made), (at.cast("long") == made.sieve_word) & (made.sieve_bits.bitwiseAND(mask) == mask), how)

    return passed


def slices(batches, rows: int):
    """Arrow batches cut to at most ``rows`` rows, so that Python work stays small whatever the session's batch size is."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def record_batch(schema: pa.Schema, *columns) -> pa.RecordBatch:
    arrays = [c if isinstance(c, pa.Array) else pa.array(c, type=f.type) for c, f in zip(columns, schema, strict=True)]
    return pa.RecordBatch.from_arrays(arrays, schema=schema)
