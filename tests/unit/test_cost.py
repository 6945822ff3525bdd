"""Cost measures over times that the line items decide."""

from __future__ import annotations

import math

import duckdb
import pytest

from freqspark import experiments  # noqa: F401  registers its queries
from freqspark import workloads as W
from freqspark.operators import measures as M

FROM_LINES = ("efficiency_table", "fractional_overhead", "scaling_slope", "speedup_table")
#: Odd lines: no key, a negative key, no flag, and a flag with one line.
LINES = [("A", 1), ("A", 1), ("A", 2), ("A", None), ("A", 4), ("R", -1), ("R", 3), ("R", 515), (None, 5), (None, 6), ("N", 0)]


@pytest.fixture(scope="module")
def lines(spark, tmp_path_factory) -> str:
    path = str(tmp_path_factory.mktemp("lines"))
    spark.createDataFrame(LINES, "l_returnflag string, l_partkey long").coalesce(1).write.parquet(f"{path}/lineitem.parquet")
    return path


def times() -> dict:
    """(flag, cores) -> the fullest worker's lines and an even share, by plain loops."""
    out = {}
    for flag in {f for f, _ in LINES}:
        keys = [k or 0 for f, k in LINES if f == flag]
        for p in W.CORES:
            loads = [sum(k % p == w for k in keys) for w in range(p)]
            out[flag, p] = (float(max(loads)), len(keys) / p)
    return out


def got(spark, name: str, path: str) -> dict:
    rows = [r.asDict() for r in W.QUERIES[name](spark, path).collect()]
    keyed = {(r.pop("series"), r.pop("p", None)): r for r in rows}
    assert len(keyed) == len(rows)
    return keyed


@pytest.mark.parametrize("name", FROM_LINES)
def test_query_reads_the_lines_and_equals_its_oracle(spark, sf_small, lines, name):
    for path, files in ((sf_small, "lineitem.parquet"), (lines, "lineitem.parquet/*.parquet")):
        db = duckdb.connect()
        db.execute(f"create view lineitem as select * from '{path}/{files}'")
        df = W.QUERIES[name](spark, path)
        assert df.inputFiles() and all("/lineitem.parquet" in f for f in df.inputFiles())
        want = db.execute(W.ORACLES[name])
        columns = [c[0] for c in want.description]
        assert df.columns == columns
        key = lambda r: tuple((x is None, str(x)) for x in r)
        assert sorted((tuple(r) for r in df.collect()), key=key) == sorted(want.fetchall(), key=key)


def test_efficiency_of_dealt_lines(spark, lines):
    t = times()
    assert got(spark, "efficiency_table", lines) == {(f, p): {"efficiency": pytest.approx(t[f, 1][0] / t[f, p][0] / p, abs=1e-4)} for f, p in t if p > 1}


def test_overhead_of_dealt_lines(spark, lines):
    want = {x: {"wall": w, "compute": c, "overhead": pytest.approx((w - c) / c, abs=1e-6)} for x, (w, c) in times().items()}
    assert got(spark, "fractional_overhead", lines) == want


def test_slope_of_dealt_lines(spark, lines):
    t, x, want = times(), [math.log(p) for p in W.CORES], {}
    for f in {f for f, _ in t}:
        y = [math.log(t[f, p][0]) for p in W.CORES]
        mx, my = sum(x) / len(x), sum(y) / len(y)
        want[f, None] = {"slope": pytest.approx(sum((a - mx) * (b - my) for a, b in zip(x, y)) / sum((a - mx) ** 2 for a in x), abs=1e-6)}
    assert got(spark, "scaling_slope", lines) == want


def test_speedup_of_dealt_lines(spark, lines):
    t = times()
    want = {(f, p): {"seconds": w, "speedup": pytest.approx(t[f, 1][0] / w, abs=1e-4), "efficiency": pytest.approx(t[f, 1][0] / w / p, abs=1e-4)} for (f, p), (w, _) in t.items()}
    assert got(spark, "speedup_table", lines) == want


def test_speedup_of_published_times(spark):
    published = {
        "threads": ((1, 1047.1, 1), (2, 443.13, 2.36), (4, 247.76, 4.22), (8, 138.36, 7.56), (16, 71.0, 14.74)),
        "messages": ((1, 874.88, 1), (32, 34.94, 25.04), (64, 17.36, 50.38), (128, 10.44, 83.79), (256, 6.05, 144.65), (512, 3.35, 261.39)),
        "hybrid": ((1, 869.83, 1), (32, 34.47, 25.24), (64, 17.38, 50.05), (128, 9.26, 93.94), (256, 4.87, 178.49), (512, 2.4, 363.11)),
    }
    table = spark.createDataFrame([(s, p, x) for s, rows in published.items() for p, x, _ in rows], "series string, p int, seconds double")
    speedup = {(s, p): x for s, rows in published.items() for p, _, x in rows}
    found = {(r["series"], r["p"]): r for r in M.scaling(table).collect()}
    assert found.keys() == speedup.keys()
    for (s, p), r in found.items():
        assert r["speedup"] == pytest.approx(speedup[s, p], rel=5e-3) and r["efficiency"] == pytest.approx(speedup[s, p] / p, rel=5e-3)
    assert all(-1 < r["slope"] < -0.85 for r in M.scaling_slope(table).collect())
