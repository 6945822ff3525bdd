"""Removal of repeated byte strings by distributed two-stage suffix sorting.

A byte goes if a string of ``length`` bytes that covers it also starts earlier in the corpus. Equal strings of that
length share the same least inner q-gram (their anchor), so suffixes are dealt by anchor and each task sorts the suffixes of
the anchors it holds; adjacent common prefixes of at least ``length`` bytes are the repeats. Before that, runs of
windows with one anchor that are equal as a whole are recognised by a 128-bit hash of anchor and content: only their
first occurrence needs sorting, every later one is a repeat throughout. Chunks do this before the shuffle, so a
large group of copies or a very common passage sends one row per chunk.

Anchors with very many different surroundings (a short line that everyone uses) are dealt by content at first and then by
whole windows instead, so no task holds an unbounded group.

Defined cases: null is empty; texts below ``length`` bytes lose nothing; equal rows (id and text) are one document and
lose the same bytes; rows that share an id but not a text stand in the order of their texts' hash; null ids come first.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from ..session import use_library
from . import textops as X
from .common import HOT_KEYS, documents, drop_written, free_shuffles, parts_for, spread_join, text_bytes, written
from .suffix_sort import common_prefixes, suffix_array

LENGTH, GRAM = 100, 32
BLOCK_BYTES = 1 << 20
HOT_SEGMENTS = 50_000
HEAT_SHARE, HEAT_LEAST = 64, 50


def least_grams(prefix: np.ndarray, n: int, length: int, gram: int) -> tuple[np.ndarray, np.ndarray]:
    """For every window start the position of its leftmost least q-gram, and the q-grams' hashes."""
    _, down = X.powers(n)
    m = n - gram + 1
    h = (prefix[gram:] - prefix[:-gram]) * down[:m]
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(32)
    low, at, width, span = h, np.arange(m, dtype=np.int32), 1, length - gram + 1

    def join(low, at, shift):
        second = low[shift:] < low[:-shift]
        return np.where(second, low[shift:], low[:-shift]), np.where(second, at[shift:], at[:-shift])

    while width * 2 <= span:
        low, at = join(low, at, width)
        width *= 2
    if width < span:
        low, at = join(low, at, span - width)
    return at, h


def merged(doc: np.ndarray, begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Union of intervals per document; inputs in any order."""
    if not len(doc):
        return doc, begin, end
    by = np.lexsort((begin, doc))
    doc, begin, end = doc[by], begin[by], end[by]
    shift = np.int64(1) << np.int64(33)
    rank = np.concatenate(([0], np.cumsum(doc[1:] != doc[:-1]))).astype(np.int64) * shift
    reach = np.maximum.accumulate(rank + end)
    fresh = np.concatenate(([True], rank[1:] + begin[1:] > reach[:-1]))
    first = np.flatnonzero(fresh)
    last = np.concatenate((first[1:] - 1, [len(doc) - 1]))
    return doc[first], begin[first], reach[last] - rank[last]


_SEGMENT = ["anchor", "content", "doc", "s", "n", "rel"]
_FOUND = ["doc", "s", "n", "anchor", "rel"]


def _batch(columns: list[np.ndarray], names: list[str]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c.astype(np.int64)) for c in columns], names=names)


def _segments(length: int, gram: int):
    """Runs of windows with one anchor: one row per distinct run of a chunk, and merged intervals (rel -1) of the rest."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in X.slices(whole):
                data, off = X.column_bytes(b.column("text"))
                count = np.maximum(np.diff(off) - length + 1, 0)
                if not count.sum():
                    continue
                ids = b.column("doc").to_numpy(zero_copy_only=False)
                prefix = X.prefix_hash(data)
                at, h = least_grams(prefix, len(data), length, gram)
                begin = np.concatenate(([0], np.cumsum(count)))
                row = np.repeat(np.arange(len(count)), count)
                start = np.arange(begin[-1]) - np.repeat(begin[:-1], count) + np.repeat(off[:-1], count)
                anchor = at[start]
                new = np.concatenate(([True], (anchor[1:] != anchor[:-1]) | (row[1:] != row[:-1])))
                first = np.flatnonzero(new)
                n = np.diff(np.append(first, len(start)))
                s, row, anchor = start[first], row[first], anchor[first].astype(np.int64)
                key = X.mix(h[anchor])
                rel = anchor - s
                content = X.mix(X.span_hash(prefix, s, s + n - 1 + length) + rel.astype(np.uint64))
                doc, inner = ids[row], s - off[row]
                by = np.lexsort((inner, doc, content, key))
                one = np.concatenate(([True], (key[by][1:] != key[by][:-1]) | (content[by][1:] != content[by][:-1])))
                keep, again = by[one], by[~one]
                d, lo, hi = merged(doc[again], inner[again], inner[again] + n[again] - 1 + length)
                yield _batch([key[keep].view(np.int64), content[keep].view(np.int64), doc[keep], inner[keep], n[keep], rel[keep]], _SEGMENT)
                if len(d):
                    yield _batch([X.mix(d.view(np.uint64)).view(np.int64), np.zeros(len(d)), d, lo, hi - lo, np.full(len(d), -1)], _SEGMENT)

    return run


def _resolve(length: int, hot: np.ndarray):
    """Rows sorted by anchor, content, place. Later equal runs become intervals; anchors with several contents are asked for.

    Only the last row and an anchor's sole content so far are held. Anchors of ``hot`` are spread over tasks by
    content, so each of their contents is asked for without knowing of the others.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last: tuple[int, int] | None = None  # anchor and content of the last row
        lone: np.ndarray | None = None  # the only content of that anchor so far
        for b in batches:
            rows = np.stack([b.column(c).to_numpy(zero_copy_only=False) for c in _SEGMENT])
            ready = rows[5] < 0
            out = [rows[[2, 3, 4, 0, 5]][:, ready]]
            rows = rows[:, ~ready]
            if rows.shape[1]:
                anchor, content = rows[0], rows[1]
                fresh = np.concatenate(([last != (anchor[0], content[0])], (anchor[1:] != anchor[:-1]) | (content[1:] != content[:-1])))
                doc, s, n = rows[2:5, ~fresh]
                out.append(np.stack([doc, s, n - 1 + length, anchor[~fresh], np.full(len(doc), -1)]))
                first = rows[:, fresh]
                known = np.isin(first[0], hot)  # anchors that have several contents whatever follows
                if lone is not None:
                    first, known = np.concatenate([lone[:, None], first], axis=1), np.concatenate([[False], known])
                elif last is not None:
                    known |= first[0] == last[0]
                lone = None
                if first.shape[1]:
                    group = np.concatenate(([0], np.cumsum(first[0, 1:] != first[0, :-1])))
                    several = (np.bincount(group) > 1)[group] | known
                    if not several[-1]:
                        lone = first[:, -1]
                    out.append(first[[2, 3, 4, 0, 5]][:, several])
                last = (anchor[-1], content[-1])
            found = np.concatenate(out, axis=1)
            if found.shape[1]:
                yield _batch(list(found), _FOUND)

    return run


def _cut_out(length: int):
    """The bytes of the asked runs; a hot anchor's windows go one by one, dealt by their own content."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in X.slices(whole):
                rows = []
                for doc, text, asks in zip(b.column("doc").to_pylist(), b.column("text").cast(pa.binary()).to_pylist(), b.column("asks").to_pylist(), strict=True):
                    for a in asks:
                        raw = text[a["s"] : a["s"] + a["n"] - 1 + length]
                        if not a["hot"]:
                            rows.append((a["anchor"], doc, a["s"], a["n"], raw))
                            continue
                        d = np.frombuffer(raw, dtype=np.uint8)
                        p = X.prefix_hash(d)
                        i = np.arange(a["n"])
                        for t, h in enumerate(X.span_hash(p, i, i + length).view(np.int64).tolist()):
                            rows.append((h, doc, a["s"] + t, 1, raw[t : t + length]))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary()), strict=True)], names=["anchor", "doc", "s", "n", "raw"])

    return run


def repeats_in_block(raws: list[bytes], doc: np.ndarray, s: np.ndarray, n: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Intervals of windows that stand earlier in another segment of the block: suffix sort, adjacent prefixes."""
    data = np.frombuffer(b"".join(raws), dtype=np.uint8)
    size = np.array([len(r) for r in raws])
    begin = np.concatenate(([0], np.cumsum(size)))[:-1]
    segment = np.repeat(np.arange(len(n)), n)
    inner = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
    window = np.full(len(data), -1, dtype=np.int64)
    window[begin[segment] + inner] = np.arange(len(segment))
    order = suffix_array(data, length + 4)
    order = order[window[order] >= 0]
    group = np.cumsum(common_prefixes(data, order, length) < length)
    w = window[order]
    d, p = doc[segment[w]], s[segment[w]] + inner[w]
    by = np.lexsort((p, d, group))
    again = by[np.concatenate(([False], group[by][1:] == group[by][:-1]))]
    return merged(d[again], p[again], p[again] + length)


def _sort_blocks(length: int, block_bytes: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        raws: list[bytes] = []
        doc: list[int] = []
        s: list[int] = []
        n: list[int] = []
        held, last = 0, None

        def flush():
            nonlocal held
            found = repeats_in_block(raws, np.array(doc), np.array(s), np.array(n), length)
            raws.clear(), doc.clear(), s.clear(), n.clear()
            held = 0
            return found

        for b in batches:
            for a, d, at, k, raw in zip(*(b.column(c).to_pylist() for c in ("anchor", "doc", "s", "n", "raw")), strict=True):
                if held >= block_bytes and a != last:
                    d_, lo, hi = flush()
                    if len(d_):
                        yield _batch([d_, lo, hi - lo], ["doc", "s", "n"])
                raws.append(raw), doc.append(d), s.append(at), n.append(k)
                held += len(raw)
                last = a
        if raws:
            d_, lo, hi = flush()
            if len(d_):
                yield _batch([d_, lo, hi - lo], ["doc", "s", "n"])

    return run


def _apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for b in X.slices(whole):
            kept, removed, spans, size = [], [], [], []
            for text, gone in zip(b.column("text").cast(pa.binary()).to_pylist(), b.column("gone").to_pylist(), strict=True):
                text = text or b""
                if gone:
                    g = np.array([(x["s"], x["s"] + x["n"]) for x in gone], dtype=np.int64)
                    _, lo, hi = merged(np.zeros(len(g), np.int64), g[:, 0], g[:, 1])
                    edges = np.concatenate(([0], np.stack([lo, hi], axis=1).ravel(), [len(text)])).tolist()
                    kept.append(b"".join(text[i:j] for i, j in zip(edges[::2], edges[1::2], strict=True)))
                    removed.append(int((hi - lo).sum()))
                    spans.append([{"s": i, "e": j} for i, j in zip(lo.tolist(), hi.tolist(), strict=True)])
                else:
                    kept.append(text)
                    removed.append(0)
                    spans.append([])
                size.append(len(text))
            names = [c for c in b.schema.names if c not in ("text", "gone")]
            kind = pa.list_(pa.struct([("s", pa.int64()), ("e", pa.int64())]))
            yield pa.RecordBatch.from_arrays(
                [*[b.column(c) for c in names], pa.array(size, pa.int64()), pa.array(removed, pa.int64()), pa.array(spans, kind), pa.array(kept, pa.binary())],
                names=[*names, "n_bytes", "n_removed", "spans", "kept"],
            )


def _numbered(df: DataFrame) -> DataFrame:
    """``df`` with ``doc``: the id where ids are unique and none is null, else a number in the defined order."""
    odd = df.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).filter("n > 1 OR doc_id IS NULL").take(1)
    if not odd:
        return df.withColumn("doc", F.col("doc_id"))
    tag = F.xxhash64(F.coalesce("text", F.lit("")))
    keys = df.select(F.col("doc_id").alias("_i"), tag.alias("_t")).distinct()
    order = [F.col("_i").asc_nulls_first(), F.col("_t").asc()]
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = written(keys.repartitionByRange(parts, *order).withColumn("_p", F.spark_partition_id()), "suffix-ranges")
    sizes = ranged.groupBy("_p").agg(F.count(F.lit(1)).alias("_c"))  # one row per range
    before = sizes.select("_p", (F.sum("_c").over(Window.orderBy("_p")) - F.col("_c")).alias("_before"))
    place = F.row_number().over(Window.partitionBy("_p").orderBy(*order))
    numbered = written(ranged.withColumn("_n", place).join(F.broadcast(before), "_p").select("_i", "_t", (F.col("_before") + F.col("_n")).cast("long").alias("doc")), "suffix-numbers")
    drop_written(ranged)
    return df.withColumn("_tag", tag).join(numbered, F.col("doc_id").eqNullSafe(F.col("_i")) & (F.col("_tag") == F.col("_t"))).drop("_i", "_t", "_tag")


def _hot_anchors(texts: DataFrame, length: int, gram: int) -> np.ndarray:
    """Anchors with the most different surroundings in one of ``HEAT_SHARE`` documents, at most ``HOT_KEYS`` of them.

    They only say which anchors to spread over tasks; results do not hang on them.
    """
    some = texts.filter(F.pmod(F.xxhash64("doc"), F.lit(HEAT_SHARE)) == 0).mapInArrow(_segments(length, gram), ", ".join(f"{c} long" for c in _SEGMENT))
    heat = some.filter("rel >= 0").groupBy("anchor").agg(F.count(F.lit(1)).alias("c")).filter(F.col("c") > HEAT_LEAST)
    return np.sort(np.array([r["anchor"] for r in heat.orderBy(F.desc("c"), "anchor").limit(HOT_KEYS).collect()], dtype=np.int64))


def remove_repeats(df: DataFrame, length: int = LENGTH, gram: int = GRAM, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """``df`` without its text, with n_bytes, n_removed, spans (removed byte ranges) and kept (remaining bytes)."""
    spark = use_library(df.sparkSession)
    plain = df.drop(*[c for c in df.columns if c in ("doc", "gone", "n_bytes", "n_removed", "spans", "kept", "_tag")])
    docs = _numbered(plain)
    texts = docs.select("doc", F.coalesce("text", F.lit("")).alias("text"))
    parts = parts_for(text_bytes(df), 24 << 20, int(spark.conf.get("spark.sql.shuffle.partitions")))
    segments = texts.mapInArrow(_segments(length, gram), ", ".join(f"{c} long" for c in _SEGMENT))
    hot = _hot_anchors(texts, length, gram)
    share = F.when(F.col("anchor").isin(hot.tolist()), F.pmod("content", F.lit(parts))).otherwise(0) if len(hot) else F.lit(0)
    dealt = segments.repartition(parts, F.col("anchor"), share).sortWithinPartitions("anchor", "content", "doc", "s")
    found = written(dealt.mapInArrow(_resolve(length, hot), ", ".join(f"{c} long" for c in _FOUND)), "suffix-found")
    free_shuffles(spark)

    asked = found.filter("rel >= 0")
    crowded = written(asked.groupBy("anchor").agg(F.count(F.lit(1)).alias("c")).filter(F.col("c") > HOT_SEGMENTS).withColumn("hot", F.lit(True)), "suffix-crowded")
    marked = spread_join(asked, crowded, ["anchor"], "c", asked.count(), "left").select("doc", F.struct("anchor", "s", "n", F.coalesce("hot", F.lit(False)).alias("hot")).alias("ask"))
    per_doc = marked.groupBy("doc").agg(F.collect_list("ask").alias("asks"))
    cut = texts.join(per_doc, "doc").mapInArrow(_cut_out(length), "anchor long, doc long, s long, n long, raw binary")
    blocks = cut.repartition(parts, "anchor").sortWithinPartitions("anchor", "doc", "s")
    sorted_out = written(blocks.mapInArrow(_sort_blocks(length, block_bytes), "doc long, s long, n long"), "suffix-sorted")
    free_shuffles(spark)

    gone = found.filter("rel < 0").select("doc", "s", "n").unionByName(sorted_out).groupBy("doc").agg(F.collect_list(F.struct("s", "n")).alias("gone"))
    kind = T.ArrayType(T.StructType([T.StructField("s", T.LongType()), T.StructField("e", T.LongType())]))
    rest = [f for f in plain.schema.fields if f.name != "text"]
    schema = T.StructType([*rest, T.StructField("n_bytes", T.LongType()), T.StructField("n_removed", T.LongType()), T.StructField("spans", kind), T.StructField("kept", T.BinaryType())])
    return docs.join(gone, "doc", "left").select(*[f.name for f in rest], "text", "gone").mapInArrow(_apply, schema)


def without_repeats(df: DataFrame, **options) -> DataFrame:
    """The rows of ``df`` with repeated strings cut from the text; rows of which no word is left go.

    A character that a cut splits is dropped as a whole. ``n_chars`` follows the new text if the table has it.
    """
    cut = remove_repeats(df, **options)
    valid, mended = F.expr("try_validate_utf8(CAST(kept AS STRING))"), F.expr("make_valid_utf8(CAST(kept AS STRING))")
    cut = cut.withColumn("text", F.coalesce(valid, F.regexp_replace(mended, "\ufffd", "")))
    if "n_chars" in df.columns:
        cut = cut.withColumn("n_chars", F.length("text").cast(df.schema["n_chars"].dataType))
    return cut.filter((F.col("n_removed") == 0) | (F.expr("btrim(text, ' \t\n\x0b\x0c\r')") != "")).select(*df.columns)


def op6_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents at 100 bytes."""
    out = remove_repeats(documents(spark, sf_dir).select("doc_id", "text"))
    return out.select("doc_id", "n_bytes", "n_removed", F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))


QUERIES = {"op6_suffix_dedup": op6_suffix_dedup}
ORACLES: dict[str, str] = {}
