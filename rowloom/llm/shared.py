"""Helpers that the training-data operators share: scratch tables, hash splits, column hygiene."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

_OWN = uuid.uuid4().hex
_FOLDERS: set[str] = set()


def shared_folder(spark: SparkSession) -> str:
    """The folder of `spark.checkpoint.dir`. Where a local session has none, a temporary one is set;
    a cluster without one is an error, since its executors share no local folder."""
    sc = spark.sparkContext
    folder = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not folder:
        if not sc.master.split("[")[0] == "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        folder = tempfile.mkdtemp(prefix="rowloom-")
        sc.setCheckpointDir(folder)
    return folder


def _remove(spark: SparkSession, folder: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
    except Exception:  # noqa: BLE001 - the session may be gone when the process ends
        pass


def written(df: DataFrame, name: str) -> DataFrame:
    """`df` as a Parquet table in the shared folder: lineage is cut and any executor can read it.

    The folder goes when the Python process ends."""
    spark = df.sparkSession
    top = f"{shared_folder(spark).rstrip('/')}/rowloom-{_OWN}"
    if top not in _FOLDERS:
        _FOLDERS.add(top)
        atexit.register(_remove, spark, top)
    path = f"{top}/{name}-{uuid.uuid4().hex[:12]}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._rowloom_path = path
    return out


def discard(*tables: DataFrame) -> None:
    """Deletes tables of `written` that nothing will read again."""
    for t in tables:
        path = getattr(t, "_rowloom_path", None)
        if path:
            _remove(t.sparkSession, path)


#: A key with more than 1 / HEAVY of all rows is joined by broadcast: there are fewer than HEAVY of them.
HEAVY = 1000


def spread_join(left: DataFrame, right: DataFrame, keys: list[str], weight: str, total: int, outer: bool = False) -> DataFrame:
    """An inner (or left outer) join on `keys` with `right`, which has each key once and in `weight` how
    many rows of `left` have it; no task gets all rows of a frequent key.

    Keys with more than total / HEAVY rows, fewer than HEAVY of them, are broadcast, and their rows are dealt
    by a hash of all their columns in place of the key. `left` is read once; its keys are not null."""
    fields = [f for f in right.schema.fields if f.name not in keys]
    heavy = right.where(F.col(weight) * HEAVY > total).select(*keys, F.struct(*[f.name for f in fields]).alias("__heavy"))
    # a zero that the optimiser cannot fold: it would take the salt out of the join's keys
    zero = F.pmod(F.xxhash64(weight), F.lit(1).cast("long"))
    light = right.where(F.col(weight) * HEAVY <= total).select(*keys, zero.alias("__salt"), F.struct(*[f.name for f in fields]).alias("__light"))
    dealt = left.join(F.broadcast(heavy), keys, "left").withColumn(
        "__salt", F.when(F.col("__heavy").isNull(), F.lit(0).cast("long")).otherwise(F.xxhash64(*left.columns).bitwiseOR(F.lit(1)))
    )
    both = dealt.join(light, [*keys, "__salt"], "left").withColumn("__found", F.coalesce("__heavy", "__light"))
    both = both if outer else both.where("__found is not null")
    return both.select(*[F.col(c) for c in left.columns], *[F.col(f"__found.{f.name}").alias(f.name) for f in fields])


#: Bits of a hash that choose a sieve's word: its 2**20 words of 64 bits at most, 42 MB, are broadcast.
SIEVE_BITS = 20


def sieve(df: DataFrame, keys: DataFrame, cols: list[str]) -> DataFrame:
    """`df` with `__hit`: false only for rows whose `cols` no row of `keys` (these columns, of the same types) has.

    An exact join may leave out the rows that are not hit, so they need not be shuffled. Keys are bits
    of a table of bounded size. Rows are hit by chance as often as its bits are set: 0.07 at 5 million
    keys, 0.45 at 40 million; at far more all are hit, and the join deals them all."""
    word, bit = F.shiftrightunsigned("__hash", 64 - SIEVE_BITS), F.expr("cast(__hash & 63 as int)")
    hashed = keys.select(F.xxhash64(*cols).alias("__hash")).select(word.alias("__word"), F.call_function("shiftleft", F.lit(1).cast("long"), bit).alias("__bit"))
    bits = hashed.groupBy("__word").agg(F.bit_or("__bit").alias("__bits"))
    marked = df.withColumn("__hash", F.xxhash64(*cols)).withColumn("__word", word).join(F.broadcast(bits), "__word", "left")
    hit = F.coalesce(F.call_function("shiftright", "__bits", bit).bitwiseAND(F.lit(1)) == 1, F.lit(False))
    return marked.select(*[F.col(c) for c in df.columns], hit.alias("__hit"))


def sifted(df: DataFrame, keys: DataFrame, cols: list[str]) -> DataFrame:
    """The rows of `df` that `sieve` hits: what an inner or semi join with `keys` needs, and some more."""
    return sieve(df, keys, cols).where("__hit").drop("__hit")


def utf8(col: Column | str) -> Column:
    """A text column as UTF-8 bytes, null as no bytes."""
    col = F.col(col) if isinstance(col, str) else col
    return F.coalesce(col.cast("string"), F.lit("")).cast("binary")


def hash_fold(doc_id: Column | str, folds: int) -> Column:
    """crc32 of the id as text, modulo `folds`; null ids fall in no fold (null)."""
    doc_id = F.col(doc_id) if isinstance(doc_id, str) else doc_id
    return F.crc32(doc_id.cast("string").cast("binary")) % F.lit(folds)


def held_out(doc_id: Column | str, folds: int, fold: int) -> Column:
    """Whether a row is never learnt from. Rows without an id count as held out in no fold."""
    return F.coalesce(hash_fold(doc_id, folds) == F.lit(fold), F.lit(False))


def clear_labels(labels: DataFrame, target: str, folds: int, fold: int) -> DataFrame:
    """One 0/1 label for each id outside the held-out fold; ids with contradicting labels count as 1."""
    return (
        labels.where(F.col("doc_id").isNotNull() & F.col(target).isNotNull() & ~held_out("doc_id", folds, fold))
        .groupBy(F.col("doc_id").alias("label_id"))
        .agg(F.max(F.col(target).cast("int")).alias("label"))
    )


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def struct_of(fields: Iterable[tuple[str, T.DataType]]) -> T.StructType:
    return T.StructType([T.StructField(n, t) for n, t in fields])


def lean(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """`run` over a partition's batches, after which the worker gives its freed memory back.

    Workers are reused: what one stage's words and batches took would else add to the next one's."""

    def wrapped(batches: Iterator) -> Iterator:
        try:
            yield from run(batches)
        finally:
            release()

    return wrapped


def release() -> None:
    import ctypes
    import gc

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass
