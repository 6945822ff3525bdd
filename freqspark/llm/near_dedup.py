"""Near-duplicate documents: banded MinHash, odd sketches, exact confirmation, components.

Documents with equal shingle sets form a class and go on as one representative. Representatives that share a band of
MinHash samples are candidates. In each band bucket every member is held against a leader, the smallest id at first, by
their odd sketches (parities of the hashed samples), whose XOR population count tells how far two sets differ; members far
from all leaders so far lead on. Pairs whose sketches allow the threshold join into clusters, linear in the members.
In a bucket that still holds several clusters, the members outside its largest one then meet all others in blocks, and
pairs that the sketches allow join clusters further: no pair that shares a band goes unseen, and a block hands on at most
one pair per joining.

Inside a cluster the links that matter are confirmed on full sets: pairs in order of their sketches' distance, skipping
those already joined. A cluster of up to SMALL documents is one group of one task and each set travels once. A larger
one is first confirmed against its leaders, which joins most of it; the members outside its largest component then meet
all others in blocks. No pair leaves a task unless it is a link, and no group is expanded into all its pairs.

The bands miss a pair at the threshold with probability (1 - t^rows)^bands, 1.4e-7 as set; the sketch's cut lies 5.3
standard deviations beyond the threshold.

Defined cases: null, empty and blank texts have no shingles and are linked with nothing. A text with fewer words than a
shingle is one shingle. Rows that repeat an id and text share class and verdict. A row without
an id takes its class's component, or none, and is kept in the latter case. Other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import use_library
from . import textops as X
from .common import documents, drop_written, free_shuffles, spread_join, written
from .components import components

BANDS, ROWS, SKETCH_BITS = 52, 6, 1024
BLOCK, SMALL, LED = 1024, 4096, 10_000


def odd_sketches(samples: np.ndarray, bits: int = SKETCH_BITS) -> np.ndarray:
    """Parity bitmap of each row of MinHash samples, as 64-bit words."""
    n, k = samples.shape
    bit = X.mix(samples ^ X.mix(np.arange(1, k + 1, dtype=np.uint64))) % np.uint64(bits)
    flat = np.bincount((np.arange(n)[:, None] * bits + bit.astype(np.int64)).ravel(), minlength=n * bits) & 1
    return np.packbits(flat.reshape(n, bits).astype(np.uint8), axis=1).view(np.uint64)


def sketch_similarity(distance: float, samples: int, bits: int = SKETCH_BITS) -> float:
    """Jaccard estimate from the population count of two sketches' XOR."""
    return 1 + bits / (4 * samples) * np.log(max(1e-9, 1 - 2 * distance / bits))


def sketch_cut(threshold: float, samples: int, bits: int = SKETCH_BITS, sigmas: float = 5.3) -> int:
    """Largest XOR count that a pair at the threshold may show."""
    gone = samples * (1 - threshold)
    share = np.exp(-4 * gone / bits)
    mean = bits / 2 * (1 - share)
    spread = samples * threshold * (1 - threshold) * (2 * share) ** 2 + bits / 4 * (1 - share**2)
    return int(np.ceil(mean + sigmas * np.sqrt(spread)))


def _longs(a: np.ndarray) -> pa.Array:
    n, k = a.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(0, n * k + 1, k), pa.int32()), pa.array(a.reshape(-1).view(np.int64)))


def _sets(b: pa.RecordBatch, words: int) -> tuple[np.ndarray, np.ndarray]:
    data, off = X.column_bytes(b.column("text"))
    w, first = X.word_hashes(data, off)
    return X.distinct_per_text(*X.shingles(w, first, words))


def _sign(words: int, bands: int, rows: int, bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in X.slices(whole):
                values, begin = _sets(b, words)
                n = np.diff(begin)
                samples = X.minhash(values, begin, bands * rows)
                keys = np.zeros((len(n), 2), dtype=np.uint64)
                full = np.flatnonzero(n > 0)
                if len(full):
                    for j in range(2):
                        keys[full, j] = np.add.reduceat(X.mix(values + np.uint64(j * 0x5851F42D4C957F2D + 1)), begin[:-1][full])
                band = np.zeros((len(n), bands), dtype=np.uint64)
                for j in range(rows):
                    band = X.mix(band * np.uint64(0x9FB21C651E98DF25) + samples[:, j::rows])
                band = X.mix(band + np.arange(bands, dtype=np.uint64))
                yield pa.RecordBatch.from_arrays(
                    [b.column("doc_id"), pa.array(n), pa.array(keys[:, 0].view(np.int64)), pa.array(keys[:, 1].view(np.int64)), _longs(band), _longs(odd_sketches(samples, bits))],
                    names=["doc_id", "n_shingles", "k1", "k2", "bands", "odd"],
                )
        X.release()

    return run


_SET_ROWS = "hub long, salt int, role int, rep long, n long, items binary"


def _emit_sets(words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in X.slices(whole):
                values, begin = _sets(b, words)
                ids = b.column("rep").to_pylist()
                out = []
                for i, seats in enumerate(b.column("seats").to_pylist()):
                    own = values[begin[i] : begin[i + 1]]
                    out += [(s["hub"], s["salt"], s["role"], ids[i], len(own), own.tobytes()) for s in seats]
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.binary()), strict=True)], names=["hub", "salt", "role", "rep", "n", "items"])

    return run


def _compare(percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, hubs = None, []
        for b in batches:
            found = []
            for hub, salt, role, rep, n, raw in zip(*(b.column(c).to_pylist() for c in ("hub", "salt", "role", "rep", "n", "items")), strict=True):
                if at != (hub, salt):
                    at, hubs = (hub, salt), []
                items = np.frombuffer(raw, dtype=np.uint64)
                if role == 0:
                    hubs.append(items)
                    continue
                for h in hubs:
                    both = int(X.find(h, items)[1].sum())
                    if 100 * both >= percent * (len(h) + n - both):
                        found.append((hub, rep))
                        break
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*found, strict=True)], names=["a", "b"])

    return run


def confirmed(docs: DataFrame, pairs: DataFrame, words: int, percent: int) -> DataFrame:
    """Those of the distinct ``pairs`` (a, b) whose full sets reach the threshold.

    Each set travels once per partner group; a hub with many partners is spread over salted copies of its own set.
    """
    per_hub = pairs.groupBy("a").agg(F.ceil(F.count(F.lit(1)) / 1000).cast("int").alias("salts"))
    sized = pairs.join(per_hub, "a")
    members = sized.select(F.col("b").alias("rep"), F.struct(F.col("a").alias("hub"), F.pmod(F.xxhash64("b"), F.col("salts")).cast("int").alias("salt"), F.lit(1).alias("role")).alias("seat"))
    hubs = per_hub.select(F.col("a").alias("rep"), F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"), "a").select("rep", F.struct(F.col("a").alias("hub"), "salt", F.lit(0).alias("role")).alias("seat"))
    seats = members.unionByName(hubs).groupBy("rep").agg(F.collect_list("seat").alias("seats"))
    texts = docs.select(F.col("doc_id").alias("rep"), "text").join(seats, "rep")
    sets = texts.mapInArrow(_emit_sets(words), _SET_ROWS)
    return sets.repartition("hub", "salt").sortWithinPartitions("hub", "salt", "role").mapInArrow(_compare(percent), "a long, b long").distinct()


def _distances(one: np.ndarray, many: np.ndarray) -> np.ndarray:
    return np.bitwise_count(one[None] ^ many).sum(axis=1, dtype=np.int64)


def _lead(cut: int, percent: int):
    """Rows sorted by bucket and id. Pairs (leader, member) that size and sketch allow; who is near no leader leads."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = None
        ids: list[int] = []
        sizes = np.zeros(0, np.int64)
        odds = np.zeros((0, 0), np.uint64)
        for b in batches:
            found = []
            odd = b.column("odd").flatten().to_numpy(zero_copy_only=False).view(np.uint64).reshape(b.num_rows, -1)
            for i, (bucket, rep, n) in enumerate(zip(b.column("bucket").to_pylist(), b.column("rep").to_pylist(), b.column("n").to_pylist(), strict=True)):
                if bucket != at:
                    at, ids, sizes, odds = bucket, [], np.zeros(0, np.int64), np.zeros((0, odd.shape[1]), np.uint64)
                near = (_distances(odd[i], odds) <= cut) & (100 * np.minimum(sizes, n) >= percent * np.maximum(sizes, n)) if ids else np.zeros(0, bool)
                if near.any():
                    found += [(ids[j], rep) for j in np.flatnonzero(near)]
                else:
                    ids, sizes, odds = [*ids, rep], np.append(sizes, n), np.concatenate([odds, odd[i : i + 1]])
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*found, strict=True)], names=["a", "b"])

    return run


def links_of(reps: list[int], comps: list[int], sets: list[np.ndarray], odds: np.ndarray, cut: int, percent: int, only: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Links that join the components ``comps`` further: nearest sketches first, pairs already joined are skipped.

    With ``only`` (a mask) a pair needs one of these on its side.
    """
    parent: dict[int, int] = {c: c for c in comps}

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    size = np.array([len(x) for x in sets])
    near: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    label = np.unique(np.array(comps), return_inverse=True)[1]
    for i in range(len(reps)) if only is None else np.flatnonzero(only):
        ok = label != label[i]
        ok[: i + 1] &= only is not None
        if only is not None:
            ok &= ~only | (np.arange(len(reps)) > i)
        ok &= 100 * np.minimum(size, size[i]) >= percent * np.maximum(size, size[i])
        j = np.flatnonzero(ok)
        if len(j):
            d = _distances(odds[i], odds[j])
            keep = d <= cut
            if keep.any():
                near.append((d[keep], np.full(keep.sum(), i), j[keep]))
    if not near:
        return []
    d, x, y = (np.concatenate(c) for c in zip(*near, strict=True))
    out = []
    for k in np.argsort(d, kind="stable"):
        i, j = int(x[k]), int(y[k])
        p, q = root(comps[i]), root(comps[j])
        if p == q:
            continue
        both = int(X.find(sets[i], sets[j])[1].sum())
        if 100 * both >= percent * (len(sets[i]) + len(sets[j]) - both):
            parent[p] = q
            out.append((min(reps[i], reps[j]), max(reps[i], reps[j])))
    return out


def bridges_of(comps: np.ndarray, size: np.ndarray, odds: np.ndarray, stray: np.ndarray, cut: int, percent: int) -> list[tuple[int, int]]:
    """Pairs of different ``comps`` with members that size and sketch allow and a stray among them; one for each joining."""
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        while parent.setdefault(x, x) != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    out = []
    rows = np.flatnonzero(stray)
    for at in range(0, len(rows), 64):
        some = rows[at : at + 64]
        may = (comps[some, None] != comps[None]) & (100 * np.minimum(size[some, None], size[None]) >= percent * np.maximum(size[some, None], size[None]))
        x, y = np.nonzero(may)
        near = np.bitwise_count(odds[some[x]] ^ odds[y]).sum(axis=1, dtype=np.int64) <= cut
        for a, b in set(zip(comps[some[x[near]]].tolist(), comps[y[near]].tolist(), strict=True)):
            p, q = root(a), root(b)
            if p != q:
                parent[p] = q
                out.append((min(a, b), max(a, b)))
    return out


def _bridge_groups(cut: int, percent: int):
    """Rows sorted by (bucket, x, y): pairs of clusters that one group joins. Side 1 are the strays of a bucket."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        left: pa.RecordBatch | None = None

        def groups(b: pa.RecordBatch, last: bool) -> tuple[list[tuple[int, int]], pa.RecordBatch | None]:
            key = np.stack([b.column(c).to_numpy() for c in ("bucket", "x", "y")])
            begin = np.flatnonzero(np.concatenate(([True], (key[:, 1:] != key[:, :-1]).any(axis=0))))
            ends = [*begin[1:], b.num_rows]
            comps, size, side = (b.column(c).to_numpy() for c in ("comp", "n", "side"))
            odds = b.column("odd").flatten().to_numpy(zero_copy_only=False).view(np.uint64).reshape(b.num_rows, -1)
            found = []
            for i, j in zip(begin, ends, strict=True) if last else zip(begin[:-1], ends[:-1], strict=True):
                found += bridges_of(comps[i:j], size[i:j], odds[i:j], side[i:j] == 1, cut, percent)
            return found, None if last else b.slice(begin[-1])

        def pairs(found: list[tuple[int, int]]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*found, strict=True)], names=["a", "b"])

        for b in batches:
            if not b.num_rows:
                continue
            if left is not None:
                b = pa.concat_batches([left, b])
            found, left = groups(b, False)
            if found:
                yield pairs(found)
        if left is not None:
            found, _ = groups(left, True)
            if found:
                yield pairs(found)

    return run


def _dealt(at: DataFrame, key: str) -> DataFrame:
    """Rows of ``at`` (``key``, rep, comp, ...) with the seats where all that lie outside their group's largest component
    (strays, side 1) meet all others of the group, in blocks; groups of one component go."""
    main = at.groupBy(key, "comp").agg(F.count(F.lit(1)).alias("c")).groupBy(key).agg(F.max_by("comp", "c").alias("main"), F.max("c").alias("n_main"), (F.sum("c") - F.max("c")).alias("n_rest"), F.sum("c").alias("c")).filter("n_rest > 0")
    deal = spread_join(at, written(main, "near-mains"), [key], "c", at.count()).withColumns({"bm": F.ceil(F.col("n_main") / BLOCK).cast("int"), "bs": F.ceil(F.col("n_rest") / BLOCK).cast("int"), "h": F.xxhash64("rep"), "stray": F.col("comp") != F.col("main")})
    seat = lambda x, y, side: F.struct(x.cast("int").alias("x"), y.cast("int").alias("y"), F.lit(side).alias("side"))
    me_s, me_m = F.pmod("h", "bs"), F.pmod("h", "bm")
    # a sole block of strays meets itself beside the first block of the others
    of_stray = F.concat(
        F.transform(F.sequence(F.lit(0), F.col("bm") - 1), lambda i: seat(i, me_s, 1)),
        F.when(F.col("bs") > 1, F.transform(F.sequence(F.lit(0), F.col("bs") - 1), lambda j: seat(-1 - F.least(j, me_s), F.greatest(j, me_s), 1))).otherwise(F.array().cast("array<struct<x:int,y:int,side:int>>")),
    )
    of_main = F.transform(F.sequence(F.lit(0), F.col("bs") - 1), lambda j: seat(me_m, j, 0))
    return deal.select(*at.columns, F.when(F.col("stray"), of_stray).otherwise(of_main).alias("seats"))


_MEMBER = "cluster long, x int, y int, side int, rep long, comp long, odd array<long>, items binary"


def _emit_members(words: int):
    """A document's set to every group of its cluster that it sits in."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in X.slices(whole):
                values, begin = _sets(b, words)
                row, seats = [], []
                for i, own in enumerate(b.column("seats").to_pylist()):
                    row += [i] * len(own)
                    seats += own
                if not row:
                    continue
                at = pa.array(row)
                raw = [values[begin[i] : begin[i + 1]].tobytes() for i in range(b.num_rows)]
                column = lambda c, t: pa.array([s[c] for s in seats], t)
                yield pa.RecordBatch.from_arrays(
                    [b.column("cluster").take(at), column("x", pa.int32()), column("y", pa.int32()), column("side", pa.int32()), b.column("rep").take(at), b.column("comp").take(at), b.column("odd").take(at), pa.array([raw[i] for i in row], pa.binary())],
                    names=["cluster", "x", "y", "side", "rep", "comp", "odd", "items"],
                )

    return run


def _link_groups(cut: int, percent: int):
    """Rows sorted by (cluster, x, y): one group's links at a time. Side 1 are the strays of a split cluster."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, rows = None, []

        def flush():
            reps, comps, sides, odds, sets = (list(c) for c in zip(*rows, strict=True))
            only = np.array(sides) == 1
            found = links_of(reps, comps, sets, np.stack(odds), cut, percent, None if only.all() or not only.any() else only)
            rows.clear()
            return pa.RecordBatch.from_arrays([pa.array([f[0] for f in found], pa.int64()), pa.array([f[1] for f in found], pa.int64())], names=["a", "b"])

        for b in batches:
            odd = b.column("odd").flatten().to_numpy(zero_copy_only=False).view(np.uint64).reshape(b.num_rows, -1)
            for i, (c, x, y, side, rep, comp, raw) in enumerate(zip(*(b.column(k).to_pylist() for k in ("cluster", "x", "y", "side", "rep", "comp", "items")), strict=True)):
                if at != (c, x, y):
                    if rows:
                        yield flush()
                    at = (c, x, y)
                rows.append((rep, comp, side, odd[i].copy(), np.frombuffer(raw, dtype=np.uint64)))
        if rows:
            yield flush()

    return run


def _grouped_links(docs: DataFrame, seated: DataFrame, words: int, cut: int, percent: int) -> DataFrame:
    """Links inside the groups that ``seated`` (rep, cluster, comp, odd, seats) deals."""
    texts = docs.select(F.col("doc_id").alias("rep"), "text").join(seated, "rep")
    members = texts.select("rep", "cluster", "comp", "odd", "seats", "text").mapInArrow(_emit_members(words), _MEMBER)
    return members.repartition("cluster", "x", "y").sortWithinPartitions("cluster", "x", "y", "rep").mapInArrow(_link_groups(cut, percent), "a long, b long")


def near_duplicates(df: DataFrame, words: int = 5, percent: int = 80, bands: int = BANDS, rows: int = ROWS, bits: int = SKETCH_BITS) -> DataFrame:
    """Per row of ``df`` (doc_id, text): doc_id, n_shingles, component_id, kept."""
    spark = use_library(df.sparkSession)
    docs = df.select("doc_id", "text")
    cut = sketch_cut(percent / 100, bands * rows, bits)
    signed = written(docs.mapInArrow(_sign(words, bands, rows, bits), "doc_id long, n_shingles long, k1 long, k2 long, bands array<long>, odd array<long>"), "near-signatures")
    full = signed.filter("n_shingles > 0 AND doc_id IS NOT NULL")
    classes = written(full.groupBy("k1", "k2").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("copies")), "near-classes")
    heads = full.withColumn("rep", F.col("doc_id")).join(classes, ["rep", "k1", "k2"]).dropDuplicates(["k1", "k2"]).select("rep", F.col("n_shingles").alias("n"), "bands", "odd")
    heads = written(heads, "near-heads")

    banded = heads.select("rep", F.explode("bands").alias("bucket"))
    shared = written(banded.groupBy("bucket").agg(F.count(F.lit(1)).alias("c"), F.min("rep").alias("hub")).filter("c > 1"), "near-shared")
    members = written(spread_join(banded, shared, ["bucket"], "c", bands * heads.count()).filter("rep <> hub").select("bucket", "hub", "rep"), "near-members")
    drop_written(shared)

    light = heads.select("rep", "n", "odd")
    of = lambda s: light.select(F.col("rep").alias(s), F.col("n").alias(f"n_{s}"), F.col("odd").alias(f"odd_{s}"))
    apart = "aggregate(zip_with(odd_a, odd_b, (x, y) -> bit_count(x ^ y)), 0, (s, x) -> s + x)"
    met_hub = written(members.select(F.col("hub").alias("a"), F.col("rep").alias("b")).distinct(), "near-met-hubs")
    hubs = written(met_hub.groupBy("a").agg(F.count(F.lit(1)).alias("c")).join(of("a"), "a"), "near-hubs")
    tested = spread_join(met_hub.join(of("b"), "b"), hubs, ["a"], "c", met_hub.count())
    tested = written(tested.select("a", "b", (F.expr(f"100 * least(n_a, n_b) >= {percent} * greatest(n_a, n_b)") & (F.expr(apart) <= cut)).alias("near")), "near-tested")
    # members far from their bucket's hub: where two of them meet, leaders among them take its place
    far = members.join(tested.filter("NOT near").select(F.col("a").alias("hub"), F.col("b").alias("rep")), ["hub", "rep"]).select("bucket", "rep")
    far = written(far, "near-far")
    crowds = written(far.groupBy("bucket").agg(F.count(F.lit(1)).alias("c")).filter("c > 1").withColumn("parts", F.ceil(F.col("c") / LED).cast("long")), "near-crowds")
    left = spread_join(far, crowds, ["bucket"], "c", far.count()).join(light, "rep")
    # a crowd of far members is led in parts; what they miss of one another, the blocks below see
    left = left.withColumn("bucket", F.xxhash64("bucket", F.pmod(F.xxhash64("rep"), "parts")))
    led = left.repartition("bucket").sortWithinPartitions("bucket", "rep").select("bucket", "rep", "n", "odd").mapInArrow(_lead(cut, percent), "a long, b long")
    stars = written(tested.filter("near").select("a", "b").unionByName(led).distinct(), "near-stars")
    drop_written(tested, met_hub, hubs, far, crowds)
    free_shuffles(spark)

    first_cluster = written(components(stars, "near-clusters").withColumnRenamed("component", "cluster").withColumnRenamed("node", "rep"), "near-first-clusters")
    # buckets that still hold several clusters, without their hubs, which have been held against every member
    labelled = members.join(first_cluster, "rep", "left").select("bucket", "rep", F.coalesce("cluster", "rep").alias("comp"))
    mixed = labelled.groupBy("bucket").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count(F.lit(1)).alias("c"))
    mixed = written(mixed.filter("lo <> hi").select("bucket", "c"), "near-mixed")
    open_ = written(spread_join(labelled, mixed, ["bucket"], "c", members.count()), "near-open")
    seated = _dealt(open_, "bucket").join(light, "rep").select("bucket", F.inline("seats"), "comp", "n", "odd")
    met = seated.repartition("bucket", "x", "y").sortWithinPartitions("bucket", "x", "y").mapInArrow(_bridge_groups(cut, percent), "a long, b long")
    joined = components(written(met.distinct(), "near-bridges"), "near-joined")
    cluster = first_cluster.join(joined, F.col("cluster") == F.col("node"), "full").select(F.coalesce("rep", "node").alias("rep"), F.coalesce("component", "cluster").alias("cluster"))
    cluster = written(cluster, "near-clusters-joined")
    drop_written(members, mixed, open_, first_cluster)
    free_shuffles(spark)
    sized = cluster.groupBy("cluster").agg(F.count(F.lit(1)).alias("size"))
    placed = written(cluster.join(sized, "cluster").join(light, "rep"), "near-placed")
    one_group = F.array(F.struct(F.lit(0).alias("x"), F.lit(0).alias("y"), F.lit(0).alias("side")))
    small = placed.filter(F.col("size") <= SMALL).select("rep", "cluster", F.col("rep").alias("comp"), "odd", one_group.alias("seats"))
    links = written(_grouped_links(docs, small, words, cut, percent), "near-links")
    large = placed.filter(F.col("size") > SMALL)
    if large.take(1):
        inside = stars.join(large.select(F.col("rep").alias("a")), "a", "left_semi")
        first = written(confirmed(docs, inside, words, percent), "near-large-links")
        so_far = components(first, "near-large").withColumnRenamed("node", "rep")
        at = written(large.join(so_far, "rep", "left").select("rep", "cluster", F.coalesce("component", "rep").alias("comp"), "odd"), "near-large-placed")
        links = written(links.unionByName(first).unionByName(_grouped_links(docs, _dealt(at, "cluster"), words, cut, percent)), "near-all-links")
    comp = components(links, "near-components")
    drop_written(heads, stars, cluster, placed)

    label = classes.join(comp.withColumnRenamed("node", "rep"), "rep", "left").withColumn("component", F.coalesce("component", "rep")).filter("copies > 1 OR component <> rep")
    label = written(label.select("k1", "k2", "component", "copies"), "near-labels")
    out = spread_join(signed.select("doc_id", "n_shingles", "k1", "k2"), label, ["k1", "k2"], "copies", signed.count(), "left")
    named = out.withColumn("component_id", F.coalesce("component", "doc_id"))
    return named.select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.col("component_id").isNull()).alias("kept"))


def deduplicated(df: DataFrame, **options) -> DataFrame:
    """The rows of ``df`` that stay: one document of each group. Rows that repeat an id stay once; rows without an id
    cannot be named by a verdict and stay."""
    found = written(near_duplicates(df, **options), "near-verdicts")
    gone = found.filter("NOT kept AND doc_id IS NOT NULL").select("doc_id").distinct()
    kept = df.join(gone, "doc_id", "left_anti").select(*df.columns)
    again = found.filter("doc_id IS NOT NULL").groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    if again.take(1):
        named = kept.filter("doc_id IS NOT NULL")
        kept = named.dropDuplicates(["doc_id"]).unionByName(kept.filter("doc_id IS NULL"))
    return kept


def op4_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents on two-word shingles at 0.8."""
    return near_duplicates(documents(spark, sf_dir), words=2)


QUERIES = {"op4_near_dedup": op4_near_dedup}
ORACLES: dict[str, str] = {}
