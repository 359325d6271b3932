"""Expressions, index, search, joins, streams and plans in Spark."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from warpspan.functions import expressions as X
from warpspan.functions import kernels as K
from warpspan.functions import udfs
from warpspan.operators import boxindex, classify, join, measures, search
from warpspan.sources import files, generate
from warpspan.sources import series as S
from warpspan.streaming import streams

N, W = 32, 3


@pytest.fixture(scope="module")
def data(spark):
    rng = np.random.default_rng(7)
    rows = rng.integers(-5, 6, (120, N)).cumsum(axis=1).astype(float)
    rows[60] = rows[10]  # a tie
    every = spark.createDataFrame([(i, r.tolist(), str(i % 3)) for i, r in enumerate(rows)], S.PACKED).repartition(4)
    queries, db = S.split_queries(every, 6)
    return rows, queries.cache(), db.cache()


def brute(rows, queries, db, k, p=1):
    out = {}
    ids = sorted(r.series_id for r in db.select("series_id").collect())
    for q in queries.collect():
        powers = K.dtw_pow(rows[ids], np.array([q.y]), W, p)
        out[q.query_id] = sorted(zip(powers.tolist(), ids, strict=True))[:k]
    return out


def answers(found):
    out = {}
    for r in sorted(found.collect(), key=lambda r: (r.query_id, r["rank"])):
        out.setdefault(r.query_id, []).append((r.dist, r.series_id))
    return out


@pytest.mark.parametrize("method", list(search.METHODS))
@pytest.mark.parametrize("k", [1, 5])
def test_all_methods_are_exact(data, method, k):
    rows, queries, db = data
    assert answers(search.nearest(queries, db, W, k=k, method=method)) == brute(rows, queries, db, k)


def test_other_norms_rounds_and_tiles(data, monkeypatch):
    rows, queries, db = data
    wanted = brute(rows, queries, db, 3, math.inf)
    assert answers(search.nearest(queries, db, W, p=math.inf, k=3, method="box_pass2")) == wanted
    two = {q: [(math.sqrt(d), i) for d, i in found] for q, found in brute(rows, queries, db, 3, 2).items()}
    assert answers(search.nearest(queries, db, W, p=2, k=3, method="box_pass2")) == two
    index = boxindex.build(db, N, page_rows=10)
    assert answers(search.search_rounds(index, queries, W, k=3)) == brute(rows, queries, db, 3)
    monkeypatch.setattr(search, "QUERY_VALUES", 2 * N)
    assert len(list(search.query_tiles(queries, W, 2 * N))) == 3
    assert answers(search.nearest(queries, db, W, k=2, method="scan_pass2", early_abandon=True)) == brute(rows, queries, db, 2)


def test_range_search_and_join(data):
    rows, queries, db = data
    eps = 120.0
    ids = [r.series_id for r in db.select("series_id").collect()]
    for method in ("brute", "scan_pass2", "box_pass2"):
        found = {(r.query_id, r.series_id, r.dist) for r in search.within(queries, db, eps, W, method=method).collect()}
        wanted = {(q.query_id, i, d) for q in queries.collect() for i, d in zip(ids, K.dtw_pow(rows[ids], np.array([q.y]), W).tolist(), strict=True) if d <= eps}
        assert found == wanted
    pairs = {(r.left_id, r.right_id) for r in join.warp_join(db, db, N, eps, W, self_join=True).collect()}
    wanted = {(a, b) for a in ids for b in ids if a < b and K.dtw_pow(rows[a], rows[b], W)[0] <= eps}
    assert pairs == wanted


def test_expressions_agree_with_kernels(spark, data):
    rows, queries, db = data
    pairs = db.select("series_id", F.col("v").alias("x")).crossJoin(F.broadcast(queries.select("query_id", "y"))).withColumn("e", X.envelope("y", W))
    made = pairs.limit(40).select(
        "x", "y", *(X.pass1_pow("x", F.col("e.lo"), F.col("e.hi"), p).alias(f"a{p}") for p in (1, 2, math.inf)),
        *(X.pass2_pow("x", "y", F.col("e.lo"), F.col("e.hi"), W, p).alias(f"b{p}") for p in (1, 2, math.inf)),
        X.dtw_pow("x", "y", N, W).alias("d"), udfs.dtw("x", "y", W, 2).alias("d2"), X.ndtw_inf("x", "y", W).alias("ninf"), X.lp_norm("x", 2).alias("norm"),
        X.separated_shortcut("x", "y").alias("cut"), udfs.pass2("x", "y", W).alias("k2"), udfs.ndtw("x", "y", W).alias("nd"),
    )
    for r in made.collect():
        x, y = np.array([r.x]), np.array([r.y])
        lo, hi = K.envelope(y, W)
        for p in (1, 2, math.inf):
            assert r[f"a{p}"] == pytest.approx(K.pass1_pow(x, lo, hi, p)[0])
            assert r[f"b{p}"] == pytest.approx(K.pass2_pow(x, y, lo, hi, W, p)[0])
        d = K.dtw_pow(x, y, W)[0]
        assert r.d == d and r.d2 == pytest.approx(math.sqrt(K.dtw_pow(x, y, W, 2)[0])) and r.ninf == K.ndtw_inf(r.x, r.y, W)
        assert r.norm == pytest.approx(np.linalg.norm(r.x)) and r.k2 <= r.nd <= d
        assert r.cut is None or r.cut == d


def test_sql_functions(spark):
    udfs.register(spark)
    row = spark.sql("SELECT warp_dtw(array(0D,0D,1D,0D), array(2D,3D,2D,2D), -1, 2) a, warp_ndtw(array(5D,7D,6D), array(1D,2D,0D), 1, 1) b, warp_pass2(array(1D), null, 1, 1) c").first()
    assert row.a == pytest.approx(math.sqrt(17)) and row.b == 15 and row.c is None
    assert spark.sql("SELECT * FROM warp_path(array(0D,1D,1D,0D), array(0D,1D,0D,0D), 1)").count() >= 4


def test_covers_and_wrong_input(spark, data):
    _, queries, db = data
    assert boxindex.floor_cover(251, 8)[-1] == (217, 251) and all(b - a == 31 for a, b in boxindex.floor_cover(251, 8)[:-1])
    for bad in (lambda: boxindex.equal_cover(10, 3), lambda: boxindex.check_cover([(0, 3), (2, 5)], 5), lambda: boxindex.floor_cover(3, 4), lambda: search.nearest(queries, db, W, p=0.5), lambda: search.nearest(queries, db, -1), lambda: search.nearest(queries, db, W, cascade=("pass2",))):
        with pytest.raises(ValueError):
            bad()
    odd = spark.createDataFrame([(1, [1.0, float("nan")], None), (2, [1.0, None], None), (3, None, None), (4, [1.0, 2.0], None), (5, [1.0], None)], S.PACKED)
    assert [r.series_id for r in S.clean(odd, 2).collect()] == [4]
    with pytest.raises(ValueError):
        S.check(odd, 2)
    empty = db.where("false")
    for method in ("scan_pass2", "box_pass2"):
        assert search.nearest(queries, empty, W, method=method).count() == 0


def test_plans(data):
    """Bounds of the JVM stay below Python, and the box scan reads no arrays."""
    _, queries, db = data
    limits = queries.select("query_id", F.lit(1e9).alias("limit"))
    plan = search.native_scan(queries, db, W, limits)._jdf.queryExecution().executedPlan().toString()
    assert plan.index("ArrowEvalPython") < plan.index("BroadcastNestedLoopJoin")  # the filter sits in the join's condition
    assert "CartesianProduct" not in plan
    index = boxindex.build(db, N, page_rows=10)
    hits = search.page_distances(index, boxindex.query_boxes(queries, W, index.cover), 1).select("query_id", "page_id")
    plan = search.reached(index, hits, 6)._jdf.queryExecution().executedPlan().toString()
    joined = plan.index("BroadcastHashJoin")
    assert "SortMergeJoin" not in plan and "Scan" in plan[joined:]  # arrays meet their pages where they lie


@pytest.mark.parametrize("method", ["box_only", "box_pass1", "box_pass2"])
@pytest.mark.parametrize("page_rows", [10, 56, boxindex.LARGE_PAGE])
def test_box_methods_go_by_pages(data, monkeypatch, method, page_rows):
    rows, queries, db = data

    def scanned(*_):
        raise AssertionError("a box method scanned")

    monkeypatch.setattr(search, "scan", scanned)
    index = boxindex.build(db, N, page_rows=page_rows)
    assert index.pages.count() == (1 if page_rows > 200 else index.pages.select("page_id").distinct().count())
    assert answers(search.nearest(queries, index, W, k=3, method=method)) == brute(rows, queries, db, 3)
    reach = search.reach_counts(queries, index, W, k=3).collect()
    assert len(reach) == 6 and all(0 < r.pages_reached <= r.pages and r.points == 114 for r in reach)
    if page_rows == 10:
        assert sum(r.points_reached for r in reach) < 6 * 114


def test_stored_index_reads_the_folders_in_reach(spark, data, tmp_path, monkeypatch):
    rows, queries, db = data
    monkeypatch.setattr(boxindex, "GROUP_PAGES", 2)
    boxindex.write(boxindex.build(db, N, page_rows=6), str(tmp_path / "i"))
    index = boxindex.read(spark, str(tmp_path / "i"))
    assert index.paged.select("page_group").distinct().count() > 3
    hits = search.page_distances(index, boxindex.query_boxes(queries, W, index.cover), 1).where("page_bound < 50").select("query_id", "page_id")
    plan = search.reached(index, hits, 6)._jdf.queryExecution().executedPlan().toString()
    assert "dynamicpruning" in plan.lower()
    assert answers(search.nearest(queries, index, W, k=2)) == brute(rows, queries, db, 2)


def test_early_abandoning_of_both_passes(data):
    rows, queries, db = data
    index = boxindex.build(db, N, page_rows=10)
    for method in ("scan_pass1", "scan_pass2", "box_pass1", "box_pass2"):
        source = index if method.startswith("box") else db
        assert answers(search.nearest(queries, source, W, k=3, method=method, early_abandon=True)) == brute(rows, queries, db, 3)
    read = {e: search.live_counters(queries, db.coalesce(1), W, early_abandon=e).agg(F.sum("samples_read")).first()[0] for e in (False, True)}
    assert read[True] <= read[False]


def test_sequential_counts_follow_the_sequential_run(data):
    rows, queries, db = data
    bounds = measures.bound_table(queries, db, W)
    assert measures.chain_violations(bounds).count() == 0
    counts = {(r.query_id, r.method): r.dtw_done for r in measures.sequential_counts(bounds, ["scan_pass1", "scan_pass2"]).collect()}
    ids = sorted(r.series_id for r in db.select("series_id").collect())
    for q in queries.collect():
        y = np.array([q.y])
        lo, hi = K.envelope(y, W)
        for method in ("scan_pass1", "scan_pass2"):
            b, done = math.inf, 0
            for i in ids:
                x = rows[i : i + 1]
                if K.pass1_pow(x, lo, hi)[0] < b and (method == "scan_pass1" or K.pass2_pow(x, y, lo, hi, W)[0] < b):
                    done += 1
                    b = min(b, K.dtw_pow(x, y, W)[0])
            assert counts[q.query_id, method] == done
    whole = {r.method: r for r in measures.distinct_survivors(bounds, ["scan_pass1", "scan_pass2"]).collect()}
    assert all(r.sketch_agrees for r in whole.values()) and whole["scan_pass2"].survivors <= whole["scan_pass1"].survivors
    boxes = {(r.query_id, r.method): r.dtw_done for r in measures.sequential_counts(bounds, ["box_only", "box_pass1", "box_pass2"]).collect()}
    for q in {q for q, _ in boxes}:
        assert boxes[q, "box_pass2"] <= boxes[q, "box_pass1"] <= boxes[q, "box_only"]


def test_files_index_and_generators(spark, data, tmp_path):
    _, queries, db = data
    for kind in ("parquet", "orc", "json", "text", "csv"):
        files.write_series(db, str(tmp_path / kind), kind)
        back = files.read_series(spark, str(tmp_path / kind), kind)
        assert {(r.series_id, tuple(r.v), r.label) for r in back.collect()} == {(r.series_id, tuple(r.v), r.label) for r in db.collect()}
    boxindex.write(boxindex.build(db, N, page_rows=16), str(tmp_path / "index"))
    index = boxindex.read(spark, str(tmp_path / "index"))
    assert answers(search.nearest(queries, index, W)) == answers(search.nearest(queries, db, W, method="brute"))
    assert generate.random_walk(spark, 5, 9).where("v[0] = 0 and size(v) = 9").count() == 5
    shapes = generate.shape_classes(spark, "control", 12)
    assert shapes.select("label").distinct().count() == 6 and shapes.where(f"size(v) = 60").count() == 12
    assert generate.whole_shapes(spark, "cbf", 9).select("label").distinct().count() == 3


def test_classes_and_normal_form(data):
    rows, queries, db = data
    said = classify.classify(db, db, W, k=3, leave_one_out=True)
    assert said.count() == db.count() and classify.accuracy(said, db).first().items == db.count()
    assert sum(classify.confusion_table(said, db).drop("label").first()) > 0
    for r in S.normalised(db).limit(5).collect():
        assert abs(np.mean(r.v)) < 1e-9 and abs(np.std(r.v) - 1) < 1e-9


def test_streamed_envelope_has_an_end():
    y, w = [3.0, 1, 4, 1, 5, 9, 2, 6], 2
    lo, hi = K.envelope(np.array([y]), w)
    assert streams.close_envelope(y[-(2 * w + 1) :], w) == list(zip(lo[0, -w:], hi[0, -w:], strict=True))
