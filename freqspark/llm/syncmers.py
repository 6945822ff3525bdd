"""Document fingerprints from closed syncmers.

A k-mer is an anchor if the smallest of its inner s-mers is its first or its last one. That depends on the k-mer's own
bytes alone, so the same passage yields the same anchors in any document. A fingerprint is a MinHash sketch of the anchors.

Defined cases: null and empty texts have the empty fingerprint; two empty fingerprints are alike (1.0), an empty and a
full one are not (0.0). A text shorter than k bytes has one anchor, itself. Equal texts have equal fingerprints. Null
ids stand before all others; rows of one id are ordered by their texts' hash. Other columns are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..session import use_library
from . import textops as X
from .common import documents, parts_for, text_bytes

K, S, SLOTS = 16, 8, 64


def closed_syncmers(data: np.ndarray, off: np.ndarray, k: int = K, s: int = S) -> tuple[np.ndarray, np.ndarray]:
    """Byte positions and k-mer hashes of all anchors in texts that lie end to end in ``data``."""
    n = len(data) - k + 1
    if n <= 0:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    prefix = X.prefix_hash(data)
    at = np.arange(len(data) - s + 1)
    inner = X.span_hash(prefix, at, at + s)
    span = k - s + 1
    least, width = inner, 1
    while width * 2 <= span:
        least = np.minimum(least[:-width], least[width:])
        width *= 2
    if width < span:
        least = np.minimum(least[: n], least[span - width : span - width + n])
    pick = (inner[:n] == least[:n]) | (inner[span - 1 : span - 1 + n] == least[:n])
    inside = np.zeros(n, dtype=bool)
    room = np.diff(off) >= k
    mark = np.zeros(n + 1, dtype=np.int32)
    np.add.at(mark, off[:-1][room], 1)
    np.add.at(mark, off[1:][room] - k + 1, -1)
    inside = np.cumsum(mark[:n]) > 0
    where = np.flatnonzero(pick & inside)
    return where, X.span_hash(prefix, where, where + k)


def sketches(texts: pa.Array, k: int = K, s: int = S, slots: int = SLOTS) -> np.ndarray:
    """One row of 16-bit MinHash samples per text; whether a text is empty is the caller's to ask."""
    data, off = X.column_bytes(texts)
    where, values = closed_syncmers(data, off, k, s)
    begin = np.searchsorted(where, off)
    bare = np.flatnonzero((np.diff(begin) == 0) & (np.diff(off) > 0))
    out = X.minhash(values, begin, slots)
    if len(bare):
        prefix = X.prefix_hash(data)
        own = X.span_hash(prefix, off[bare], off[bare + 1])
        out[bare] = X.minhash(own, np.arange(len(bare) + 1), slots)
    return (out & np.uint64(0xFFFF)).astype(">u2")


def alike(a: np.ndarray, b: np.ndarray, a_full: np.ndarray, b_full: np.ndarray) -> np.ndarray:
    """Share of equal samples, row by row, with the empty cases as the module states them."""
    same = (a == b).mean(axis=1)
    return np.where(a_full & b_full, same, np.where(a_full == b_full, 1.0, 0.0))


def _hex(rows: np.ndarray, full: np.ndarray) -> list[str]:
    return [r.tobytes().hex() if f else "" for r, f in zip(rows, full, strict=True)]


def anchors(df: DataFrame, key: str = "doc_id", text: str = "text", k: int = K, s: int = S) -> DataFrame:
    """All anchors as rows (key, pos, anchor): byte position and 64-bit k-mer hash, for positional matching."""
    use_library(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in X.slices(whole, "t"):
                data, off = X.column_bytes(b.column("t"))
                where, values = closed_syncmers(data, off, k, s)
                row = np.searchsorted(off, where, side="right") - 1
                yield pa.RecordBatch.from_arrays([b.column("k").take(pa.array(row)), pa.array(where - off[row]), pa.array(values.view(np.int64))], names=[key, "pos", "anchor"])

    schema = T.StructType([T.StructField(key, df.schema[key].dataType), T.StructField("pos", T.LongType()), T.StructField("anchor", T.LongType())])
    return df.select(F.col(key).alias("k"), F.col(text).alias("t")).mapInArrow(run, schema)


_OUT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def _pairs(k: int, s: int, slots: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None  # the last row seen, which waits for its successor
        bucket = None
        for whole in batches:
            for b in X.slices(whole, limit=1 << 20):
                ids, marks = b.column("doc_id").to_pylist(), b.column("ahead").to_pylist()
                buckets, texts = b.column("bucket").to_pylist(), [t or "" for t in b.column("text").to_pylist()]
                sketch = sketches(pa.array(texts, pa.large_string()), k, s, slots)
                full = np.array([t != "" for t in texts])
                if held is not None:
                    ids, marks, buckets, texts = [held[0], *ids], [held[1], *marks], [held[2], *buckets], [held[3], *texts]
                    sketch, full = np.concatenate([held[4][None], sketch]), np.concatenate([[held[5]], full])
                held = (ids[-1], marks[-1], buckets[-1], texts[-1], sketch[-1], full[-1])
                out = [i for i in range(len(ids) - 1) if not marks[i] and buckets[i] == buckets[i + 1]]
                if not out:
                    continue
                edited = []
                for i in out:
                    half = len(texts[i]) // 2
                    edited.append(texts[i][: len(texts[i]) - half] + texts[i + 1][:half])
                changed = sketches(pa.array(edited, pa.large_string()), k, s, slots)
                edited_full = np.array([t != "" for t in edited])
                at = np.array(out)
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array([ids[i] for i in out], pa.int64()),
                        pa.array([len(texts[i]) for i in out], pa.int64()),
                        pa.array([hashlib.sha256(t.encode("utf-8", "surrogatepass")).hexdigest() for t in edited]),
                        pa.array(_hex(sketch[at], full[at])),
                        pa.array(_hex(changed, edited_full)),
                        pa.array(alike(sketch[at], changed, full[at], edited_full)),
                        pa.array(alike(sketch[at], sketch[at + 1], full[at], full[at + 1])),
                    ],
                    names=["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"],
                )

    return run


def fingerprints_with_edit(df: DataFrame, k: int = K, s: int = S, slots: int = SLOTS, part_bytes: int = 16 << 20) -> DataFrame:
    """Fingerprint of each document and of its edit, whose second half is the head of the next document by id.

    One shuffle of the texts into id ranges. The first document of each range is also sent to the range before it, as
    the successor of that range's last one; ranges and their first ids (one number each) are all the driver holds.
    """
    spark = use_library(df.sparkSession)
    lowest = -(1 << 63)
    rows = df.select("doc_id", F.coalesce("doc_id", F.lit(lowest)).alias("place"), "text")
    parts = parts_for(text_bytes(df), part_bytes)
    if parts > 1:
        bounds = sorted({int(x) for x in rows.approxQuantile("place", [i / parts for i in range(1, parts)], 0.25 / parts)})
    else:
        bounds = []
    cut = np.array(bounds, dtype=np.int64)

    @F.pandas_udf("int")
    def bucket_of(place):
        import pandas as pd

        return pd.Series(np.searchsorted(cut, place.to_numpy(), side="right").astype(np.int32))

    placed = rows.withColumn("bucket", bucket_of("place"))
    firsts = sorted((r["bucket"], r["first"]) for r in rows.select("place").withColumn("bucket", bucket_of("place")).groupBy("bucket").agg(F.min("place").alias("first")).collect())
    if not firsts:
        return spark.createDataFrame([], _OUT)
    before = {first: firsts[i - 1][0] for i, (_, first) in enumerate(firsts)}  # the first of all follows the last range

    @F.pandas_udf("array<struct<bucket:int,ahead:boolean>>")
    def seats(place, bucket):
        import pandas as pd

        return pd.Series([[(b, False), (before[p], True)] if p in before else [(b, False)] for p, b in zip(place, bucket, strict=True)])

    seated = placed.withColumn("seat", F.explode(seats("place", "bucket"))).select("doc_id", "place", "text", "seat.bucket", "seat.ahead")
    ordered = seated.repartitionByRange(len(firsts), "bucket").sortWithinPartitions("bucket", "ahead", "place", F.xxhash64("text"))
    return ordered.select("doc_id", "bucket", "ahead", "text").mapInArrow(_pairs(k, s, slots), _OUT)


def op10_syncmers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents and their edits."""
    return fingerprints_with_edit(documents(spark, sf_dir))


QUERIES = {"op10_syncmers": op10_syncmers}
ORACLES: dict[str, str] = {}
