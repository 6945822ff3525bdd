"""What the operators of this subpackage share on the Spark side: written tables, sizes, reading."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space of the word pattern `[^\x20\x09-\x0D]+`.
SPACES = " \t\n\x0b\x0c\r"

_FREE_FILES = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"  # a session setting of Spark 4.1
_written: dict[str, SparkSession] = {}
_local_base: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Only a local master may go without that setting (tests); a cluster without it is an error,
    because a folder of one machine is not visible to the others.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _local_base:
        _local_base.append(tempfile.mkdtemp(prefix="freqspark-"))
    return _local_base[0]


def written(df: DataFrame, name: str, by: str | None = None) -> DataFrame:
    """``df`` written as a table in the shared folder and read again: lineage ends here and survives executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/freqspark-{spark.sparkContext.applicationId}/{name}-{uuid.uuid4().hex[:12]}"
    out = df.write.option("compression", "zstd")
    was = spark.conf.get(_FREE_FILES, None)
    spark.conf.set(_FREE_FILES, "true")  # the table replaces its shuffles: their files go when the write ends
    try:
        (out.partitionBy(by) if by else out).parquet(path)
    finally:
        spark.conf.unset(_FREE_FILES) if was is None else spark.conf.set(_FREE_FILES, was)
    _written[path] = spark
    out = spark.read.schema(df.schema).parquet(path)
    out._written_path = path
    return out


def drop_written(*tables: DataFrame) -> None:
    """Delete tables of :func:`written` that no later step reads, and let Spark free finished shuffles."""
    for t in tables:
        path = getattr(t, "_written_path", None)
        if path and path in _written:
            _delete(path)


def drop_part(table: DataFrame, part: str) -> None:
    """Delete one partition folder of a table of :func:`written` that no later step reads."""
    _remove(table.sparkSession, f"{table._written_path}/{part}")


def _delete(path: str) -> None:
    _remove(_written.pop(path), path)


def _remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


@atexit.register
def _clean() -> None:
    for path in list(_written):
        try:
            _delete(path)
        except Exception:  # the JVM has gone already; the cluster's own clean-up of the folder remains
            _written.pop(path, None)


def free_shuffles(spark: SparkSession) -> None:
    """Ask the driver to collect garbage, after which the context cleaner removes files of finished shuffles."""
    import gc

    gc.collect()
    spark.sparkContext._jvm.System.gc()


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet")


def crc_mod(column: str | Column, n: int) -> Column:
    """crc32 of the id's decimal text, modulo n; null ids give null."""
    c = F.col(column) if isinstance(column, str) else column
    return F.crc32(c.cast("string").cast("binary")) % F.lit(n)


def text_bytes(df: DataFrame, column: str = "text") -> int:
    """Bytes of text in the table: one number from one narrow pass."""
    return int(df.agg(F.sum(F.octet_length(column)).alias("b")).first()["b"] or 0)


def parts_for(total: float, each: float, least: int = 1) -> int:
    """As many partitions as keep each near ``each``; grows with the input."""
    return max(least, int(total // each) + 1)


#: A key is hot beyond one part in this many of a join's rows, so there are at most this many hot keys.
HOT_KEYS = 1000


def spread_join(many: DataFrame, one: DataFrame, keys: list[str], count: str, total: int, how: str = "inner") -> DataFrame:
    """``many`` joined to ``one``, which has each key once; its column ``count`` (the key's rows in ``many``) goes.

    Rows of a key with more than a thousandth of ``total`` are dealt by key and share, and the key's row of ``one`` goes to
    every share, so no key is left to one task. At most ``HOT_KEYS`` keys can be that hot: the broadcast is bounded.
    """
    each = max(1000, total // HOT_KEYS)
    shares = F.greatest(F.ceil(F.col(count) / each), F.lit(1)).cast("int")
    hot = one.filter(F.col(count) > each).select(*keys, shares.alias("__shares"))
    dealt = many.join(F.broadcast(hot), keys, "left").withColumn("__share", F.pmod(F.xxhash64(*many.columns), F.coalesce("__shares", F.lit(1))).cast("int")).drop("__shares")
    held = one.withColumn("__share", F.explode(F.sequence(F.lit(0), shares - 1))).drop(count)
    return dealt.join(held, [*keys, "__share"], how).drop("__share")


#: Bytes of text that a fitting sample holds of each class, beside its limit of rows.
SAMPLE_BYTES = 24 << 20


def row_key(df: DataFrame, key: str = "doc_id") -> Column:
    """What tells rows apart in a draw: the id, or the row's place where it has none, so copies of a text fall one by one."""
    place = F.monotonically_increasing_id()
    return F.coalesce(F.col(key).cast("long"), place) if key in df.columns else place


def drawn(share: Column, seed: int, *key: Column | str) -> Column:
    """Whether a row falls into a share of all rows."""
    return F.pmod(F.xxhash64(F.lit(seed), *key), F.lit(1 << 30)) / F.lit(float(1 << 30)) < share


def bounded_sample(df: DataFrame, by: str, limit: int | dict, key: Column | str, text: str | None = None, most_bytes: int = SAMPLE_BYTES) -> DataFrame:
    """Near ``limit`` rows (or its entry) of each value of ``by`` and, with ``text``, near ``most_bytes`` of it at most, chosen
    row by row through a hash of ``key``: for fitting, at any input size.

    Classes within both bounds stay whole; values without an entry in ``limit`` go. One count per class is all the driver holds.
    """
    size = F.sum(F.octet_length(text)) if text else F.lit(0)
    shares = {}
    for r in df.groupBy(by).agg(F.count(F.lit(1)).alias("n"), size.cast("double").alias("b")).collect():
        most = limit.get(r[by], 0) if isinstance(limit, dict) else limit
        shares[r[by]] = min(1.0, most / r["n"], most_bytes / r["b"] if r["b"] else 1.0)
    share = F.lit(1.0)
    for value, s in sorted(shares.items(), key=str):
        if s < 1:
            share = F.when(F.col(by) == F.lit(value), F.lit(s)).otherwise(share)
    return df.withColumn("__k", key if isinstance(key, Column) else F.col(key)).filter(drawn(share, 1, "__k")).drop("__k")
