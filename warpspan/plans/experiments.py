"""Registered queries of measures, experiments, applications, streams and round trips."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from warpspan.functions import expressions as X
from warpspan.operators import boxindex, classify, measures, search
from warpspan.plans import oracles as O
from warpspan.plans.methods import D, FIX, N, PAGE_ROWS, Q, QUERY_COUNTS, W, answers_sql, indexed, workload
from warpspan.plans.registry import query, register
from warpspan.sources import files, generate
from warpspan.sources import series as S
from warpspan.sources.tables import table
from warpspan.streaming import streams

SCANS, BOXES = ["scan_pass1", "scan_pass2"], ["box_only", "box_pass1", "box_pass2"]
METHODS = SCANS + BOXES
_COUNTS = "candidates, after_box, after_pass1, after_pass2, dtw_done"


def _bounds(spark: SparkSession, sf_dir: str, name: str = FIX, w: int = W, d: int = D) -> DataFrame:
    """The table of all bounds of a workload."""
    return measures.bound_table(*workload(spark, sf_dir, name), w, d=d)


def _counts(spark: SparkSession, sf_dir: str, name: str, w: int, methods: list[str]) -> DataFrame:
    """Sequential counts of a workload, from the rows that can change one."""
    made = measures.counting_table(*workload(spark, sf_dir, name), w)
    return measures.sequential_counts(made.rows.withColumnRenamed("box0", "box"), methods, candidates=F.lit(made.sizes[0]))


_M = f"WITH RECURSIVE {O.measured(FIX, Q, N, W)}"
register("prune_counts_scan", lambda s, d: measures.sequential_counts(_bounds(s, d), SCANS), f"{_M} {O.counts(SCANS)}")
register("prune_counts_box", lambda s, d: measures.sequential_counts(_bounds(s, d), BOXES), f"{_M} {O.counts(BOXES)}")
register(
    "stage_histogram",
    lambda s, d: measures.stage_histogram(_bounds(s, d)),
    f"""{_M} SELECT query_id, CASE WHEN box >= b THEN 'box' WHEN pass1 >= b THEN 'pass1' WHEN pass2 >= b THEN 'pass2' ELSE 'dtw' END AS stage, count(*) AS candidates
    FROM (SELECT *, coalesce(min(dtw) OVER (PARTITION BY query_id ORDER BY box, series_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 'inf'::DOUBLE) AS b FROM m) GROUP BY 1, 2""",
)
register(
    "comparisons_scan",
    lambda s, d: measures.scan_comparisons(*workload(s, d), W),
    f"WITH {O.split(FIX, Q)}, {O.bounds(N, W)} SELECT query_id, sum(CASE WHEN x > hi THEN 1 ELSE 2 END)::BIGINT AS comparisons, (2 * count(*))::BIGINT AS most FROM clamped GROUP BY 1",
)
register(
    "comparison_limits",
    lambda s, d: measures.comparison_limits(measures.sequential_counts(_bounds(s, d), ["scan_pass2"]), N),
    f"{_M} SELECT query_id, ((2 * candidates + 3) * {N})::BIGINT AS limit_pass1, ((2 * candidates + 3) * {N} + 5 * after_pass1 * {N})::BIGINT AS limit_pass2 FROM ({O.counts(['scan_pass2'])})",
)
register(
    "second_pass_comparisons",
    lambda s, d: (lambda qs, db: measures.second_pass_comparisons(measures.bound_table(qs, db, W), qs, db, W).select("query_id", (F.col("comparisons") <= F.col("most")).alias("holds"), "most"))(*workload(s, d)),
    f"{_M} SELECT query_id, TRUE AS holds, (5 * {N} * after_pass1)::BIGINT AS most FROM ({O.counts(['scan_pass2'])}) WHERE after_pass1 > 0",
)
register(
    "cells_done",
    lambda s, d: measures.cells_done(measures.sequential_counts(_bounds(s, d), METHODS), N, W),
    f"{_M} SELECT query_id, method, (dtw_done * {N * (2 * W + 1) - W * (W + 1)})::BIGINT AS cells FROM ({O.counts(METHODS)})",
)
_RATIO = "floor({0} * 1000 / dtw)"
register(
    "tightness",
    lambda s, d: measures.tightness(_bounds(s, d)).select(*(F.col(c).cast("bigint").alias(c) for c in ("box_mean", "box_median", "pass1_mean", "pass1_median", "pass2_mean", "pass2_median", "pairs"))),
    f"{_M} SELECT " + ", ".join(f"floor(sum({_RATIO.format(b)}) / count(*))::BIGINT AS {b}_mean, quantile_disc({_RATIO.format(b)}, 0.5)::BIGINT AS {b}_median" for b in ("box", "pass1", "pass2")) + ", count(*) AS pairs FROM m WHERE dtw > 0",
)
register(
    "bound_chain_violations",
    lambda s, d: measures.chain_violations(_bounds(s, d)).select("query_id", "series_id"),
    f"{_M} SELECT query_id, series_id FROM m WHERE NOT (box <= pass1 AND pass1 <= pass2 AND pass2 <= dtw AND dtw <= lp)",
)


@query("error_within_limits", f"{_M}, e AS (SELECT query_id, sum(greatest(hi - y, y - lo)) AS most FROM q_env GROUP BY 1) SELECT query_id, max(dtw - pass1)::BIGINT AS largest_error, max(most)::BIGINT AS most, max(dtw - pass1) <= max(most) AS holds FROM m JOIN e USING (query_id) GROUP BY 1")
def error_within_limits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first bound's true error against the limit that the query alone gives."""
    queries, _ = workload(spark, sf_dir)
    limits = queries.withColumn("e", X.envelope("y", W)).select("query_id", X.pass1_error_limit("y", "e.lo", "e.hi").alias("most"))
    errors = _bounds(spark, sf_dir).groupBy("query_id").agg(F.max(F.col("dtw") - F.col("pass1")).alias("largest_error"))
    both = errors.join(limits, "query_id")
    return both.select("query_id", F.col("largest_error").cast("bigint").alias("largest_error"), F.col("most").cast("bigint").alias("most"), (F.col("largest_error") <= F.col("most")).alias("holds"))


@query("pages_touched", f"""WITH RECURSIVE {O.split(FIX, Q)}, {O.bounds(N, W)}, {O.warp(N, W)}, {O.pages(N, W, PAGE_ROWS)}
 SELECT query_id, count(*) FILTER (WHERE page_bound <= b) AS touched, count(*) AS pages FROM page_hits JOIN (SELECT query_id, min(dtw) AS b FROM warp GROUP BY 1) USING (query_id) GROUP BY 1""")
def pages_touched(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages of eight points within each query's nearest distance."""
    queries, index = indexed(spark, sf_dir, PAGE_ROWS)
    limits = search.nearest(queries, index, W).select("query_id", F.col("dist").alias("limit"))
    return measures.pages_touched(index, queries, W, limits)


def _power(counts: DataFrame, *by: str) -> DataFrame:
    return measures.pruning_power(counts, ["method", *by]).select(*by, "method", F.col("pruned_ppm").cast("bigint").alias("pruned_ppm"), "dtw_done")


def _power_sql(rows: str, *by: str) -> str:
    keys = ", ".join([*by, "method"])
    return f"SELECT {keys}, floor((sum(candidates) - sum(dtw_done)) * 1000000 / sum(candidates))::BIGINT AS pruned_ppm, sum(dtw_done)::BIGINT AS dtw_done FROM ({rows}) GROUP BY {keys}"


def _counted_sql(name: str, w: int, methods: list[str] = METHODS, d: int = D) -> str:
    n = S.FIXTURES[name][1]
    return f"WITH RECURSIVE {O.counted_only(name, QUERY_COUNTS.get(name, Q), n, w, d)} {O.counts(methods)}"


#: Workloads whose samples are too many for SQL; tests hold their counts against a plain sequential run.
NO_TWIN = {"char_walk"}
#: What a band of 5, 10 and 20 % of n is.
BANDS = lambda n: (n // 20, n // 10, n // 5)
FRACTIONS = (0.2, 0.4, 0.6, 0.8, 1.0)
DIMENSIONS = (4, 6, 8, 10, 12, 16)


def _unless_long(name: str, sql: str) -> str | None:
    return None if name in NO_TWIN else sql


# Pruning power of all methods on every workload.
for _name, (_, _n) in S.FIXTURES.items():
    register(
        f"pruning_{_name}",
        lambda s, d, name=_name, n=_n: _power(_counts(s, d, name, n // 10, METHODS)),
        _unless_long(_name, _power_sql(f"({_counted_sql(_name, _n // 10)})")),
    )


def _fractions_sql(name: str) -> str:
    n, listed = S.FIXTURES[name][1], ", ".join(map(str, FRACTIONS))
    parts = f""", places AS (SELECT series_id, row_number() OVER (ORDER BY (z * z + 1) % 1000003, series_id) AS place, count(*) OVER () AS places FROM (SELECT series_id, (series_id * 7919 + 1299709) % 1000003 AS z FROM db)),
 parts AS (SELECT b.*, fraction FROM bounds b JOIN places USING (series_id) CROSS JOIN (SELECT unnest([{listed}])::DOUBLE AS fraction) WHERE place <= ceil(fraction * places))"""
    made = O.counted_only(name, QUERY_COUNTS.get(name, Q), n, n // 10, source="parts", keys="fraction, query_id", more=parts)
    return f"WITH RECURSIVE {made} {_power_sql(O.counts(METHODS, 'm', 'fraction, query_id'), 'fraction')}"


def fraction_sweep(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Pruning power as the database grows: the first ceil(f * N) series in hash order."""
    n = S.FIXTURES[name][1]
    queries, db = workload(spark, sf_dir, name)
    places = S.fraction_rank(db.select("series_id"))
    reached = F.array(*(F.ceil(F.lit(f) * F.col("places")) for f in FRACTIONS))
    first = places.select("series_id", F.size(F.filter(reached, lambda most: most < F.col("place"))).alias("first"))
    made = measures.counting_table(queries, db.join(first, "series_id"), n // 10, parts=len(FRACTIONS))
    of = F.array(*(F.struct(F.lit(k).alias("part"), F.lit(f).alias("fraction"), F.lit(size).alias("size")) for k, (f, size) in enumerate(zip(FRACTIONS, made.sizes, strict=True))))
    rows = made.rows.withColumnRenamed("box0", "box").select("*", F.inline(of)).where("part >= first")
    # A fraction and a query make one sequence.
    keyed = rows.withColumn("own", F.col("query_id")).withColumn("query_id", F.struct("fraction", "own"))
    return _power(measures.sequential_counts(keyed, METHODS, ["fraction", "query_id"], F.col("size")), "fraction")


def d_sweep(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Pruning power by the number of sums; one table has the boxes of all."""
    made = measures.counting_table(*workload(spark, sf_dir, name), S.FIXTURES[name][1] // 10, DIMENSIONS)
    boxes = {d: made.rows.withColumnRenamed(f"box{k}", "box") for k, d in enumerate(DIMENSIONS)}
    return _swept(DIMENSIONS, "d", lambda d: measures.sequential_counts(boxes[d], BOXES, candidates=F.lit(made.sizes[0])))


for _name in (FIX, "supplier_week_walk", "supplier_day_walk", "part_qty_raw", "user_raw", "char_walk", "word_walk"):
    register(f"fraction_sweep_{_name}", lambda s, d, name=_name: fraction_sweep(s, d, name), _unless_long(_name, _fractions_sql(_name)))


def _swept_sql(values: tuple[int, ...], name: str, sql) -> str:
    return _power_sql(" UNION ALL ".join(f"SELECT {v} AS {name}, * FROM ({sql(v)})" for v in values), name)


def _swept(values: tuple[int, ...], name: str, counts) -> DataFrame:
    return _power(search._union([counts(v).withColumn(name, F.lit(v)) for v in values]), name)


for _name in (FIX, "supplier_week_walk", "embedding_walk", "word_walk"):
    register(
        f"w_sweep_{_name}",
        lambda s, d, name=_name, n=S.FIXTURES[_name][1]: _swept(BANDS(n), "w", lambda w: _counts(s, d, name, w, METHODS)),
        _swept_sql(BANDS(S.FIXTURES[_name][1]), "w", lambda w, name=_name: _counted_sql(name, w)),
    )
for _name in (FIX, "embedding_walk", "word_walk"):
    register(
        f"d_sweep_{_name}",
        lambda s, d, name=_name: d_sweep(s, d, name),
        _swept_sql(DIMENSIONS, "d", lambda k, name=_name: _counted_sql(name, S.FIXTURES[name][1] // 10, BOXES, k)),
    )


def _two_widths(spark: SparkSession, sf_dir: str) -> DataFrame:
    return search._union([measures.sequential_counts(_bounds(spark, sf_dir, w=w), METHODS).withColumn("w", F.lit(w)) for w in (4, 8)])


_TWO = " UNION ALL ".join(f"SELECT {w} AS w, * FROM (WITH RECURSIVE {O.measured(FIX, Q, N, w)} {O.counts(METHODS)})" for w in (4, 8))
register(
    "pruning_cube",
    lambda s, d: _two_widths(s, d).cube("w", "method").agg(F.sum("candidates").alias("candidates"), F.sum("dtw_done").alias("dtw_done")),
    f"SELECT w, method, sum(candidates)::BIGINT AS candidates, sum(dtw_done)::BIGINT AS dtw_done FROM ({_TWO}) GROUP BY CUBE (w, method)",
)
register(
    "pruning_rollup",
    lambda s, d: _two_widths(s, d).rollup("w", "method").agg(F.sum("dtw_done").alias("dtw_done")),
    f"SELECT w, method, sum(dtw_done)::BIGINT AS dtw_done FROM ({_TWO}) GROUP BY ROLLUP (w, method)",
)
register(
    "pruning_pivot",
    lambda s, d: _two_widths(s, d).groupBy("w").pivot("method", METHODS).sum("dtw_done"),
    f"SELECT w, {', '.join(f'''sum(dtw_done) FILTER (WHERE method = '{m}')::BIGINT AS {m}''' for m in METHODS)} FROM ({_TWO}) GROUP BY w",
)
register(
    "pruning_ratios",
    lambda s, d: measures.pruning_ratios(measures.sequential_counts(_bounds(s, d), BOXES), "box_pass1", "box_pass2").select(*(F.floor(F.col(c) * 1000).cast("bigint").alias(c) for c in ("pruned_ratio", "survivor_ratio"))),
    f"""WITH t AS (SELECT method, sum(candidates) AS c, sum(dtw_done) AS d FROM ({_counted_sql(FIX, W, BOXES)}) GROUP BY 1), a AS (SELECT * FROM t WHERE method = 'box_pass1'), b AS (SELECT * FROM t WHERE method = 'box_pass2')
    SELECT floor(((b.c - b.d) / b.c) / ((a.c - a.d) / a.c) * 1000)::BIGINT AS pruned_ratio, floor((a.d / a.c) / (b.d / b.c) * 1000)::BIGINT AS survivor_ratio FROM a CROSS JOIN b""",
)
_SURVIVE = {m: " AND ".join(f"{t} < b" for t in O.SEQUENTIAL[m][0]) for m in METHODS}
register(
    "approx_survivors",
    lambda s, d: measures.distinct_survivors(_bounds(s, d), METHODS),
    f"{_M} " + " UNION ALL ".join(
        f"SELECT '{m}' AS method, count(DISTINCT series_id) AS survivors, TRUE AS sketch_agrees FROM (SELECT *, coalesce(min(dtw) OVER (PARTITION BY query_id ORDER BY {O.SEQUENTIAL[m][1]} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 'inf'::DOUBLE) AS b FROM m) WHERE {test}"
        for m, test in _SURVIVE.items()
    ),
)


def _abandoning(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Samples that the bounds read and distances computed, with and without early abandoning; they depend on how the data are cut."""
    n, outs = S.FIXTURES[name][1], []
    queries, db = workload(spark, sf_dir, name)
    index = boxindex.build(db, n, min(D, n), boxindex.SMALL_PAGE)
    for method in ("box_pass1", "box_pass2"):
        for early in (False, True):
            made = search.live_counters(queries, index, n // 10, method=method, early_abandon=early)
            sums = made.agg(*(F.sum(c).alias(c) for c in ("candidates", "after_box", "after_pass1", "after_pass2", "dtw_done", "samples_read")))
            outs.append(sums.select(F.lit(method).alias("method"), F.lit(early).alias("early_abandon"), "*"))
    return search._union(outs)


for _name in ("embedding_walk", "word_walk"):
    register(f"early_abandon_{_name}", lambda s, d, name=_name: _abandoning(s, d, name))


# Classification.
_LOO = f"""WITH RECURSIVE {O.FIXTURES['nation_month']}, packed AS (SELECT series_id, list(val::DOUBLE ORDER BY pos) AS v FROM long GROUP BY series_id),
 {O.warp(80, 8, '1', 'SELECT a.series_id AS query_id, b.series_id, b.v AS x, a.v AS y FROM packed a JOIN packed b ON a.series_id <> b.series_id')},
 near AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dtw, series_id) AS r FROM warp),
 named AS (SELECT n_nationkey::BIGINT AS series_id, r_name AS label FROM nation JOIN region ON n_regionkey = r_regionkey),
 votes AS (SELECT query_id, label, count(*) AS votes FROM near JOIN named USING (series_id) WHERE r <= 3 GROUP BY 1, 2),
 guess AS (SELECT query_id, label AS predicted FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY votes DESC, label) AS r FROM votes) WHERE r = 1)"""


def _nations(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    nations = S.nation_month(spark, sf_dir)
    return classify.classify(nations, nations, 8, k=3, leave_one_out=True), nations


register("classify_nations", lambda s, d: _nations(s, d)[0], f"{_LOO} SELECT * FROM guess")
register("confusion", lambda s, d: classify.confusion(*_nations(s, d)), f"{_LOO} SELECT label, predicted, count(*) AS items FROM guess JOIN named ON query_id = series_id GROUP BY 1, 2")
register("accuracy", lambda s, d: classify.accuracy(*_nations(s, d)), f"{_LOO} SELECT count(*) AS items, count(*) FILTER (WHERE label = predicted) AS right FROM guess JOIN named ON query_id = series_id")


#: Table column that names a workload's classes, as SQL relation ``(series_id, label)``.
CLASSES = {
    "embeddings": ("embedding_walk", "SELECT vec_id AS series_id, label::VARCHAR AS label FROM embeddings"),
    "lang": ("word_walk", "SELECT doc_id AS series_id, lang AS label FROM documents"),
    "quality": ("word_walk", "SELECT doc_id AS series_id, quality::VARCHAR AS label FROM labels"),
    "toxic": ("word_walk", "SELECT doc_id AS series_id, toxic::VARCHAR AS label FROM labels"),
}


def _classes(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    """Held-out series named by their nearest neighbour, with the true label beside."""
    name = CLASSES[kind][0]
    queries, train = workload(spark, sf_dir, name, Q)
    test = queries.select(F.col("query_id").alias("series_id"), F.col("y").alias("v"), "label")
    if kind in ("quality", "toxic"):
        known = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("series_id"), F.col(kind).cast("string").alias("label"))
        test, train = (rows.drop("label").join(known, "series_id") for rows in (test, train))
    return classify.compared(classify.classify(test, train, S.FIXTURES[name][1] // 10), test)


def _classes_sql(kind: str) -> str:
    name, named = CLASSES[kind]
    n = S.FIXTURES[name][1]
    return f"""WITH RECURSIVE {O.split(name, Q)}, {O.bounds(n, n // 10)}, named AS ({named}),
 wanted AS (SELECT query_id, series_id FROM (SELECT b.*, min(lp) OVER (PARTITION BY query_id) AS most FROM bounds b JOIN named USING (series_id) WHERE query_id IN (SELECT series_id FROM named)) WHERE pass2 <= most),
 {O.warp(n, n // 10, '1', 'SELECT query_id, series_id, v AS x, y FROM wanted JOIN db USING (series_id) JOIN q USING (query_id)')},
 near AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dtw, series_id) AS r FROM warp)
 SELECT query_id, a.label AS predicted, b.label AS label FROM near JOIN named a ON near.series_id = a.series_id JOIN named b ON query_id = b.series_id WHERE r = 1"""


for _kind in CLASSES:
    register(f"classify_{_kind}", lambda s, d, k=_kind: _classes(s, d, k), _classes_sql(_kind))


# Generators.
_NOISE = "(z * 7 + z // 1009) % 2001 - 1000"


def _noise_sql(salt: int) -> str:
    inner = f"(id * 7919 + pos * 104729 + {salt * 1299709}) % 1000003"
    return f"(SELECT {_NOISE} FROM (SELECT (y * y + {salt}) % 1000003 AS z FROM (SELECT {inner} AS y)))"


def _keys(spark: SparkSession, sf_dir: str, name: str, key: str) -> DataFrame:
    """The ids that a table's rows give to a generator."""
    return table(spark, sf_dir, name).select(F.col(key).alias("id"))


register(
    "gen_whole_walk",
    lambda s, d: S.unpack(generate.whole_walk(s, _keys(s, d, "customer", "c_custkey"), 64)),
    f"""WITH flat AS (SELECT id::BIGINT AS series_id, pos::INT AS pos, {' + '.join(_noise_sql(k) for k in (11, 12, 13))} AS val FROM (SELECT c_custkey AS id FROM customer) CROSS JOIN range(1, 65) g(pos))
    SELECT series_id, pos, (sum(64 * val - s) OVER (PARTITION BY series_id ORDER BY pos))::BIGINT AS val FROM (SELECT *, sum(val) OVER (PARTITION BY series_id) AS s FROM flat)""",
)


@query("gen_random_walk", "SELECT 255 * count(*)::BIGINT AS steps, TRUE AS from_zero, TRUE AS centred, TRUE AS unit_steps FROM customer")
def gen_random_walk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A walk of 256 samples for each customer: where they start, and mean and variance of their steps, to five deviations of each."""
    walks = generate.random_walk(spark, _keys(spark, sf_dir, "customer", "c_custkey"), 256)
    step = F.zip_with(F.slice("v", 2, 255), F.slice("v", 1, 255), lambda a, b: a - b)
    sums = walks.select(
        F.element_at("v", 1).alias("first"), F.aggregate(step, F.lit(0.0), lambda t, x: t + x).alias("s"), F.aggregate(step, F.lit(0.0), lambda t, x: t + x * x).alias("q"), F.size(step).alias("c")
    ).agg(F.sum("c").alias("steps"), F.max(F.abs("first")).alias("first"), F.sum("s").alias("s"), F.sum("q").alias("q"))
    mean, square = F.col("s") / F.col("steps"), F.col("q") / F.col("steps")
    return sums.select("steps", (F.col("first") == 0).alias("from_zero"), (F.abs(mean) < 5 / F.sqrt("steps")).alias("centred"), (F.abs(square - mean * mean - 1) < 5 * F.sqrt(2 / F.col("steps"))).alias("unit_steps"))


#: Each class's expected mean, by the rules of the generator.
LEVELS = {
    "cbf": {"flat": 3.0, "up": 1.5, "down": 1.5},
    "control": {"normal": 30.0, "cycle": 30.0, "rise": 40.3, "fall": 19.7, "step_up": 36.9, "step_down": 23.1},
}
WALKS = 50_000


def _levels(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    """Series of each class, one for each order, and whether their mean is what the class should have."""
    shapes = generate.shape_classes(spark, kind, _keys(spark, sf_dir, "orders", "o_orderkey"))
    mean = F.aggregate("v", F.lit(0.0), lambda t, x: t + x) / F.size("v")
    level = F.element_at(F.create_map(*(F.lit(x) for pair in LEVELS[kind].items() for x in pair)), F.col("label"))
    means = shapes.groupBy("label").agg(F.count("*").alias("items"), F.avg(mean).alias("mean"))
    return means.select("label", "items", (F.abs(F.col("mean") - level) < 0.6).alias("at_level"))


for _kind, _classes_of in LEVELS.items():
    register(
        f"gen_shapes_{_kind}",
        lambda s, d, k=_kind: _levels(s, d, k),
        f"SELECT list_extract({list(_classes_of)}, (o_orderkey % {len(_classes_of)} + 1)::INT) AS label, count(*)::BIGINT AS items, TRUE AS at_level FROM orders GROUP BY 1",
    )


def _generated(spark: SparkSession, series: DataFrame, w: int) -> DataFrame:
    return _power(measures.sequential_counts(measures.bound_table(*S.split_queries(series, Q), w), METHODS))


# The published sizes: 50,000 series and 20 queries.
register("pruning_gen_cbf", lambda s, d: _generated(s, generate.whole_shapes(s, "cbf", WALKS), 12))
register("pruning_gen_control", lambda s, d: _generated(s, generate.whole_shapes(s, "control", WALKS), 6))
register("pruning_gen_walk", lambda s, d: _generated(s, generate.whole_walk(s, WALKS, 256), 25))


# Streams, compared with batch SQL over the same rows.
_C = "floor(value * 100 + 0.5)::BIGINT"
register(
    "stream_tumbling",
    lambda s, d: streams.drained(streams.tumbling(streams.event_stream(s, d))),
    f"""SELECT user_id, date_trunc('day', ts)::TIMESTAMP AS start, date_trunc('day', ts)::TIMESTAMP + INTERVAL 1 DAY AS "end", count(*) AS n, sum({_C})::BIGINT AS cents FROM events GROUP BY 1, 2, 3""",
)
register(
    "stream_sliding",
    lambda s, d: streams.drained(streams.sliding(streams.event_stream(s, d))),
    f"""SELECT user_id, w AS start, w + INTERVAL 2 DAY AS "end", count(*) AS n, sum({_C})::BIGINT AS cents
    FROM (SELECT *, unnest([date_trunc('day', ts)::TIMESTAMP, date_trunc('day', ts)::TIMESTAMP - INTERVAL 1 DAY]) AS w FROM events) GROUP BY 1, 2, 3""",
)
register(
    "stream_session",
    lambda s, d: streams.drained(streams.sessions(streams.event_stream(s, d))),
    f"""SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 6 HOUR AS "end", count(*) AS n, sum({_C})::BIGINT AS cents FROM
    (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, g""",
)
register("stream_once", lambda s, d: streams.drained(streams.once(streams.event_stream(s, d)).select("event_id", "user_id"), "append"), "SELECT event_id, user_id FROM events")


def _of_type(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    return streams.event_stream(spark, sf_dir).where(F.col("event_type") == kind)


register(
    "stream_interval_join",
    lambda s, d: streams.drained(streams.paired(_of_type(s, d, "click"), _of_type(s, d, "view"), "60 minutes"), "append"),
    "SELECT a.user_id, a.event_id AS left_id, b.event_id AS right_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'view' AND b.ts BETWEEN a.ts - INTERVAL 60 MINUTE AND a.ts + INTERVAL 60 MINUTE",
)
_ORDERED = f"SELECT user_id, event_id, {_C} AS c, row_number() OVER u AS pos, count(*) OVER (PARTITION BY user_id) AS n FROM events WINDOW u AS (PARTITION BY user_id ORDER BY ts, event_id)"
register(
    "stream_envelope",
    lambda s, d: streams.drained(streams.envelope_stream(streams.event_stream(s, d), 3), "append"),
    f"SELECT user_id, pos, event_id, min(c) OVER f AS lo, max(c) OVER f AS hi FROM ({_ORDERED}) WINDOW f AS (PARTITION BY user_id ORDER BY pos ROWS BETWEEN 3 PRECEDING AND 3 FOLLOWING) QUALIFY pos <= n - 3",
)
PATTERN_N, PATTERN_EPS = 16, 60_000


def _patterns(spark: SparkSession, sf_dir: str) -> dict[int, list[float]]:
    """The first samples of the three smallest users."""
    rows = S.user_events(spark, sf_dir).orderBy("series_id").limit(3).collect()
    return {r.series_id: list(r.v[:PATTERN_N]) for r in rows}


register(
    "stream_pattern_watch",
    lambda s, d: streams.drained(streams.watch_patterns(streams.event_stream(s, d), _patterns(s, d), 2, PATTERN_EPS), "append"),
    f"""WITH RECURSIVE o AS ({_ORDERED}), p AS (SELECT user_id AS query_id, list(c::DOUBLE ORDER BY pos) AS y FROM o WHERE n >= 48 AND pos <= {PATTERN_N} GROUP BY 1 ORDER BY 1 LIMIT 3),
    x AS (SELECT user_id, event_id AS series_id, pos, list(c::DOUBLE) OVER (PARTITION BY user_id ORDER BY pos ROWS BETWEEN {PATTERN_N - 1} PRECEDING AND CURRENT ROW) AS x FROM o QUALIFY pos >= {PATTERN_N}),
    {O.warp(PATTERN_N, 2, '1', 'SELECT query_id, series_id, x, y FROM x CROSS JOIN p')}
    SELECT user_id, series_id AS event_id, query_id AS pattern, dtw::BIGINT AS dist FROM warp JOIN x USING (series_id) WHERE dtw <= {PATTERN_EPS}""",
)


@query("stream_late_rows", "SELECT count(*) AS late FROM events WHERE ts < TIMESTAMP '2024-01-11' AND ts < (SELECT max(ts) FROM events WHERE ts >= TIMESTAMP '2024-01-21') - INTERVAL 1 HOUR")
def stream_late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Thirds of the month in the wrong order, one a trigger: rows are late from the second trigger after a watermark on."""
    place = streams.shared_folder(spark)
    events = table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    third = F.least(F.lit(2), F.floor((F.dayofmonth("ts") - 1) / 10))
    for part in (2, 1, 0):
        events.where(third == part).coalesce(1).write.mode("append").parquet(f"{place}/in")
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{place}/in")
    return spark.createDataFrame([(streams.late_rows(stream),)], "late bigint")


@query("stream_nearest", answers_sql("part_qty_walk", Q, 24, 2))
def stream_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each batch's first 24 samples of a part go to the stored index of all others."""
    place = streams.shared_folder(spark)
    queries, db = workload(spark, sf_dir, "part_qty_walk")
    queries.select("query_id", "y").repartition(2).write.parquet(f"{place}/segments")
    boxindex.write(boxindex.build(db, 24, D, boxindex.SMALL_PAGE), f"{place}/index")
    segments = spark.readStream.schema("query_id bigint, y array<double>").option("maxFilesPerTrigger", 1).parquet(f"{place}/segments")
    streams.nearest_online(segments, boxindex.read(spark, f"{place}/index"), 2, f"{place}/answers").awaitTermination()
    found = spark.read.parquet(f"{place}/answers").drop("batch")
    return found.select("query_id", F.col("rank").cast("int").alias("rank"), "series_id", F.col("dist").cast("bigint").alias("dist"))


# Round trips.
@query("text_import_roundtrip", O.series("tag_walk"))
def text_import_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Series written as lines of text and read back."""
    place = streams.shared_folder(spark)
    files.write_series(S.fixture(spark, sf_dir, "tag_walk"), f"{place}/lines", "text")
    return S.unpack(files.read_series(spark, f"{place}/lines", "text"))


@query("index_roundtrip", answers_sql())
def index_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Answers from an index that was written, read, and given more series."""
    place = streams.shared_folder(spark)
    queries, db = workload(spark, sf_dir)
    first = db.where("series_id % 2 = 0")
    boxindex.write(boxindex.build(first, N, D, page_rows=16), place)
    whole = boxindex.append(boxindex.read(spark, place), db.where("series_id % 2 = 1"), page_rows=16)
    found = search.nearest(queries, whole, W, method="box_pass2")
    return found.select("query_id", F.col("rank").cast("int").alias("rank"), "series_id", F.col("dist").cast("bigint").alias("dist"))


@query("unreached_candidates", f"WITH RECURSIVE {O.measured(FIX, Q, N, W)} SELECT series_id FROM db WHERE series_id NOT IN (SELECT series_id FROM m WHERE dtw <= 1000000)")
def unreached_candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Series that no query comes near to, by an anti join."""
    queries, db = workload(spark, sf_dir)
    return db.join(search.within(queries, db, 1_000_000, W), "series_id", "left_anti").select("series_id")


@query("event_type_counts", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def event_type_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.count("*").alias("n"))
