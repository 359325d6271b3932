"""Registered queries of single methods: builders, distances, envelopes, bounds, index, search.

The default workload is ``supplier_month_walk`` (83 samples, band 8) with
twenty held-out queries; the shape workloads have fifty. The box methods run
on an index with pages of 4096 bytes (56 points), and again on larger ones.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from warpspan.functions import expressions as X
from warpspan.functions import kernels, udfs
from warpspan.operators import boxindex, join, search
from warpspan.plans import oracles as O
from warpspan.plans.registry import query, register
from warpspan.sources import series as S
from warpspan.sources.tables import table

FIX, N, W, Q, D = "supplier_month_walk", 83, 8, 20, 8
#: Workloads with another number of queries than Q: the shapes, and one of 25 series.
QUERY_COUNTS = {"word_walk": 50, "word_length_raw": 50, "char_walk": 50, "nation_month": 5}
NORMS = {"p1": (1, "1"), "p2": (2, "2"), "inf": (math.inf, "inf")}


def workload(spark: SparkSession, sf_dir: str, name: str = FIX, n_queries: int | None = None) -> tuple[DataFrame, DataFrame]:
    return S.split_queries(S.fixture(spark, sf_dir, name), n_queries or QUERY_COUNTS.get(name, Q))


def indexed(spark: SparkSession, sf_dir: str, page_rows: int = boxindex.SMALL_PAGE) -> tuple[DataFrame, boxindex.BoxIndex]:
    queries, db = workload(spark, sf_dir)
    return queries, boxindex.build(db, N, D, page_rows)


def _paired(queries: DataFrame, db: DataFrame) -> DataFrame:
    return db.select("series_id", F.col("v").alias("x")).crossJoin(F.broadcast(queries))


def _pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``query_id, series_id, x, y`` of the default workload; the few queries are broadcast."""
    queries, db = workload(spark, sf_dir)
    return _paired(queries.select("query_id", "y"), db)


def _enveloped(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same with ``lo, hi``: a query's envelope is made once, below the join."""
    queries, db = workload(spark, sf_dir)
    ready = queries.select("query_id", "y", X.envelope("y", W).alias("e"))
    return _paired(ready.select("query_id", "y", F.col("e.lo").alias("lo"), F.col("e.hi").alias("hi")), db)


def _value(name: str, column) -> list:
    return ["query_id", "series_id", column.cast("bigint").alias(name)]


# Builders.
for _name, (_build, _) in S.FIXTURES.items():
    register(f"series_{_name}", lambda spark, d, b=_build: S.unpack(b(spark, d)), O.series(_name))


@query("gap_fill", O.series("supplier_month_raw"))
def gap_fill(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The month grid by an outer join with the sparse sums."""
    month = (F.year("l_shipdate") - 1995) * 12 + F.month("l_shipdate")
    sums = S._supplier_sums(spark, sf_dir, month, S.MONTHS)
    out = S.gap_filled(sums, sums.select("series_id").distinct(), S.MONTHS)
    return out.select("series_id", "pos", F.col("val").cast("bigint").alias("val"))


@query("sparse_map_series", f"SELECT o_custkey AS series_id, {O._MONTH.format('o_orderdate')} AS pos, count(*) AS val FROM orders GROUP BY ALL")
def sparse_map_series(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.sparse_map(spark, sf_dir).select("series_id", F.col("pos").cast("bigint").alias("pos"), "val")


@query("turn_length_series", "SELECT conv_id AS series_id, row_number() OVER (PARTITION BY conv_id ORDER BY turn, length(text))::INT AS pos, length(text)::BIGINT AS val FROM conversations")
def turn_length_series(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.unpack(S.turn_lengths(spark, sf_dir))


@query("json_value_series", """SELECT user_id AS series_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id)::INT AS pos,
  (props ->> '$.k')::BIGINT AS val FROM events""")
def json_value_series(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A number inside JSON as a series."""
    events = table(spark, sf_dir, "events").select("user_id", "ts", "event_id", F.get_json_object("props", "$.k").cast("bigint").alias("val"))
    place = F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    return events.select(F.col("user_id").alias("series_id"), place.alias("pos"), "val")


@query("asof_grid", """WITH g AS (SELECT user_id, t FROM (SELECT DISTINCT user_id FROM events) CROSS JOIN (SELECT unnest(range(TIMESTAMP '2024-01-01', TIMESTAMP '2024-01-31', INTERVAL 1 DAY)) AS t)),
 v AS (SELECT user_id, ts, arg_max(floor(value * 100 + 0.5)::BIGINT, event_id) AS cents FROM events GROUP BY ALL)
 SELECT g.user_id AS series_id, (date_diff('day', TIMESTAMP '2024-01-01', g.t) + 1)::INT AS pos, v.cents AS val FROM g ASOF LEFT JOIN v ON g.user_id = v.user_id AND g.t >= v.ts""")
def asof_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last value at or before each day, by a union with the grid and a forward fill."""
    events = table(spark, sf_dir, "events").select("user_id", "ts", "event_id", F.floor(F.col("value") * 100 + 0.5).cast("bigint").alias("cents"))
    days = F.explode(F.sequence(F.lit(0), F.lit(29)))
    grid = events.select("user_id").distinct().select("user_id", days.alias("day"))
    start = F.lit("2024-01-01").cast("timestamp_ntz")
    ticks = grid.select("user_id", (start + F.make_dt_interval("day")).alias("ts"), F.lit(2**62).alias("event_id"), F.lit(None).cast("bigint").alias("cents"), (F.col("day") + 1).alias("pos"))
    both = events.withColumn("pos", F.lit(None).cast("int")).unionByName(ticks)
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    filled = both.withColumn("val", F.last("cents", ignorenulls=True).over(before))
    return filled.where("pos is not null").select(F.col("user_id").alias("series_id"), "pos", "val")


@query("held_out_split", f"WITH {O.split(FIX, Q)} SELECT series_id, 'candidate' AS role FROM db UNION ALL SELECT query_id, 'query' FROM q")
def held_out_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    queries, db = workload(spark, sf_dir)
    return db.select("series_id", F.lit("candidate").alias("role")).union(queries.select("query_id", F.lit("query")))


# Distances.
for _tag, (_p, _sp) in NORMS.items():
    register(
        f"lp_distances_{_tag}",
        lambda spark, d, p=_p: join.lp_pairs(*workload(spark, d), p).select(*_value("power", F.col("power"))),
        f"WITH {O.split(FIX, Q)}, {O.bounds(N, W, _sp)} SELECT query_id, series_id, lp::BIGINT AS power FROM bounds",
    )
    register(
        f"dtw_{_tag}",
        lambda spark, d, p=_p: _pairs(spark, d).select(*_value("power", udfs.dtw("x", "y", W, p, rooted=False))),
        f"WITH RECURSIVE {O.split(FIX, Q)}, {O.warp(N, W, _sp)} SELECT query_id, series_id, dtw::BIGINT AS power FROM warp",
    )
    register(
        f"pass1_{_tag}",
        lambda spark, d, p=_p: _enveloped(spark, d).select(*_value("power", X.pass1_pow("x", "lo", "hi", p))),
        f"WITH {O.split(FIX, Q)}, {O.bounds(N, W, _sp)} SELECT query_id, series_id, pass1::BIGINT AS power FROM bounds",
    )
    register(
        f"pass2_{_tag}",
        lambda spark, d, p=_p: _enveloped(spark, d).select(*_value("power", X.pass2_pow("x", "y", "lo", "hi", W, p))),
        f"WITH {O.split(FIX, Q)}, {O.bounds(N, W, _sp)} SELECT query_id, series_id, pass2::BIGINT AS power FROM bounds",
    )
register("dtw_unbanded", lambda s, d: _pairs(s, d).select(*_value("power", udfs.dtw("x", "y", None))), f"WITH RECURSIVE {O.split(FIX, Q)}, {O.warp(N, N)} SELECT query_id, series_id, dtw::BIGINT AS power FROM warp")
register("dtw_w0", lambda s, d: _pairs(s, d).select(*_value("power", udfs.dtw("x", "y", 0))), f"WITH {O.split(FIX, Q)}, {O.bounds(N, 0)} SELECT query_id, series_id, lp::BIGINT AS power FROM bounds")
register(
    "dtw_native",
    lambda s, d: _pairs(s, d).select(*_value("power", X.dtw_pow("x", "y", N, W))),
    f"WITH RECURSIVE {O.split(FIX, Q)}, {O.warp(N, W)} SELECT query_id, series_id, dtw::BIGINT AS power FROM warp",
)
register(
    "ndtw_inf",
    lambda s, d: _pairs(s, d).select(*_value("power", X.ndtw_inf("x", "y", W))),
    f"""WITH {O.split(FIX, Q)}, {O.bounds(N, W)},
    cells AS (SELECT a.query_id, a.series_id, a.pos AS i, b.pos AS j, abs(a.x - b.y) AS c FROM clamped a JOIN q_long b ON a.query_id = b.query_id AND abs(a.pos - b.pos) <= {W}),
    near AS (SELECT query_id, series_id, min(c) AS g FROM cells GROUP BY query_id, series_id, i UNION ALL SELECT query_id, series_id, min(c) FROM cells GROUP BY query_id, series_id, j)
    SELECT query_id, series_id, max(g)::BIGINT AS power FROM near GROUP BY ALL""",
)
register(
    "ndtw_sorted_p1",
    lambda s, d: _pairs(s, d).select(*_value("power", udfs.ndtw_sorted("x", "y"))),
    f"WITH RECURSIVE {O.split(FIX, Q)}, {O.warp(N, N, '1', 'SELECT query_id, series_id, list_sort(v) AS x, list_sort(y) AS y FROM db CROSS JOIN q')} SELECT query_id, series_id, dtw::BIGINT AS power FROM warp",
)
register("ndtw_banded_p1", lambda s, d: _pairs(s, d).select(*_value("power", udfs.ndtw("x", "y", W))))
# With a band of one each point has three partners, and the cheapest cover follows from four sums carried from point to point.
register(
    "ndtw_band_of_one",
    lambda s, d: _pairs(s, d).select(*_value("power", udfs.ndtw("x", "y", 1))),
    f"""WITH RECURSIVE {O.split(FIX, Q)}, pairs AS (SELECT query_id, series_id, v AS x, y FROM db CROSS JOIN q),
    states(query_id, series_id, i, none, mine, other, twice) USING KEY (query_id, series_id) AS (
      SELECT query_id, series_id, 1, 0.0::DOUBLE, 'inf'::DOUBLE, 'inf'::DOUBLE, 'inf'::DOUBLE FROM pairs
      UNION
      SELECT s.query_id, s.series_id, i + 1, least(twice, least(none, mine, other) + abs(x[i] - y[i])),
        abs(x[i + 1] - y[i]) + least(mine, twice, least(none, other) + abs(x[i] - y[i])), abs(x[i] - y[i + 1]) + least(other, twice, least(none, mine) + abs(x[i] - y[i])),
        abs(x[i + 1] - y[i]) + abs(x[i] - y[i + 1]) + least(none, mine, other, twice)
      FROM states s JOIN pairs p ON s.query_id = p.query_id AND s.series_id = p.series_id WHERE i < {N})
    SELECT query_id, s.series_id, least(twice, least(none, mine, other) + abs(x[{N}] - y[{N}]))::BIGINT AS power FROM states s JOIN pairs USING (query_id, series_id)""",
)

BANDS = (0, 4, 8, 16, 83)


@query("band_sweep", "WITH RECURSIVE " + O.split(FIX, Q) + ",\n" + ",\n".join(O.warp(N, w, name=f"warp{w}") for w in BANDS) + "\nSELECT *, coalesce(dtw <= lag(dtw) OVER (PARTITION BY query_id, series_id ORDER BY w), TRUE) AS falls FROM (" + " UNION ALL ".join(f"SELECT query_id, series_id, {w} AS w, dtw::BIGINT AS dtw FROM warp{w}" for w in BANDS) + ")")
def band_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The distance falls as the band widens."""
    pairs = _pairs(spark, sf_dir)
    each = pairs.select("query_id", "series_id", *(udfs.dtw("x", "y", w).cast("bigint").alias(f"w{w}") for w in BANDS))
    rows = each.select("query_id", "series_id", F.inline(F.array(*(F.struct(F.lit(w).alias("w"), F.col(f"w{w}").alias("dtw")) for w in BANDS))))
    last = F.lag("dtw").over(Window.partitionBy("query_id", "series_id").orderBy("w"))
    return rows.withColumn("falls", F.coalesce(F.col("dtw") <= last, F.lit(True)))


@query("separated_pairs", f"""WITH RECURSIVE {O.split(FIX, Q)}, {O.warp(N, W, '1', 'SELECT query_id, series_id, list_transform(v, lambda t: t + 10000000) AS x, y FROM db CROSS JOIN q')}
 SELECT query_id, series_id, dtw::BIGINT AS shortcut, dtw::BIGINT AS dtw FROM warp""")
def separated_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Series moved apart: the distance is the plain l1 distance."""
    apart = _pairs(spark, sf_dir).withColumn("x", F.transform("x", lambda v: v + 10_000_000))
    return apart.select("query_id", "series_id", X.separated_shortcut("x", "y").cast("bigint").alias("shortcut"), udfs.dtw("x", "y", W).cast("bigint").alias("dtw"))


# Envelopes and bounds.
_ENVELOPE_SQL = f"""WITH {O.FIXTURES[FIX]} SELECT series_id, pos, min(val) OVER f AS lo, max(val) OVER f AS hi FROM long
  WINDOW f AS (PARTITION BY series_id ORDER BY pos ROWS BETWEEN {W} PRECEDING AND {W} FOLLOWING)"""


@query("envelope_long", _ENVELOPE_SQL)
def envelope_long(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The definition, as a window over long series."""
    frame = Window.partitionBy("series_id").orderBy("pos").rowsBetween(-W, W)
    return S.unpack(S.fixture(spark, sf_dir, FIX)).select("series_id", "pos", F.min("val").over(frame).alias("lo"), F.max("val").over(frame).alias("hi"))


def _envelope_rows(frame: DataFrame) -> DataFrame:
    zipped = frame.select("series_id", F.posexplode(F.arrays_zip(F.col("e.lo").alias("lo"), F.col("e.hi").alias("hi"))).alias("p", "z"))
    return zipped.select("series_id", (F.col("p") + 1).alias("pos"), F.col("z.lo").cast("bigint").alias("lo"), F.col("z.hi").cast("bigint").alias("hi"))


for _form, _envelope in (("packed", udfs.envelope), ("native", X.envelope), ("queues", udfs.envelope_by_queues)):
    register(f"envelope_{_form}", lambda s, d, f=_envelope: _envelope_rows(S.fixture(s, d, FIX).select("series_id", f("v", W).alias("e"))), _ENVELOPE_SQL)


@query("envelope_comparisons")
def envelope_comparisons(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Comparisons of the single-pass envelope against its limit of three a sample."""
    made = S.fixture(spark, sf_dir, FIX).select("series_id", udfs.envelope_by_queues("v", W).alias("e"))
    return made.select("series_id", F.col("e.comparisons").alias("comparisons"), F.lit(3 * N).cast("bigint").alias("most"), (F.col("e.comparisons") <= 3 * N).alias("holds"))


@query("clamp_long", f"WITH {O.split(FIX, Q)}, {O.bounds(N, W)} SELECT query_id, series_id, pos::INT AS pos, h::BIGINT AS h FROM clamped")
def clamp_long(spark: SparkSession, sf_dir: str) -> DataFrame:
    clamped = _enveloped(spark, sf_dir).select("query_id", "series_id", F.posexplode(X.clamp("x", "lo", "hi")).alias("p", "h"))
    return clamped.select("query_id", "series_id", (F.col("p") + 1).alias("pos"), F.col("h").cast("bigint").alias("h"))


register("gap2_p1", lambda s, d: _enveloped(s, d).select(*_value("power", X.gap2_pow("x", "y", "lo", "hi", W))), f"WITH {O.split(FIX, Q)}, {O.bounds(N, W)} SELECT query_id, series_id, gap2::BIGINT AS power FROM bounds")
register(
    "pass1_error_limit",
    lambda s, d: workload(s, d)[0].withColumn("e", X.envelope("y", W)).select("query_id", X.pass1_error_limit("y", "e.lo", "e.hi").cast("bigint").alias("most")),
    f"WITH {O.split(FIX, Q)}, {O.bounds(N, W)} SELECT query_id, sum(greatest(hi - y, y - lo))::BIGINT AS most FROM q_env GROUP BY query_id",
)


@query("anchor_bound_midpoint", f"""WITH {O.split(FIX, Q)}, {O.bounds(N, W)}, mid AS (SELECT *, CASE WHEN x > hi THEN floor((x + hi) / 2) WHEN x < lo THEN ceil((x + lo) / 2) ELSE x END AS m FROM clamped)
 SELECT query_id, series_id, sum(abs(x - m))::BIGINT AS bound, sum(abs(m - y))::BIGINT AS most_error, TRUE AS admissible FROM mid GROUP BY 1, 2""")
def anchor_bound_midpoint(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The generic bound for an h half-way to the envelope, its error limit, and whether h is allowed."""
    pairs = _enveloped(spark, sf_dir)
    half = F.zip_with(
        F.zip_with("x", "lo", lambda x, lo: F.when(x < lo, F.ceil((x + lo) / 2).cast("double")).otherwise(x)), "hi", lambda x, hi: F.when(x > hi, F.floor((x + hi) / 2).cast("double")).otherwise(x)
    )
    made = pairs.withColumn("h", half)
    return made.select(
        "query_id", "series_id", X.anchor_bound("x", "h").cast("bigint").alias("bound"), X.anchor_error_limit("h", "y").cast("bigint").alias("most_error"), X.is_admissible("x", "h", "lo", "hi").alias("admissible")
    )


@query("explain_bounds", f"""WITH {O.split(FIX, Q)}, {O.bounds(N, W)} SELECT query_id, series_id, pos::INT AS pos, x::BIGINT AS xi, y::BIGINT AS yi, lo::BIGINT AS lo, hi::BIGINT AS hi, h::BIGINT AS clamped,
  lo2::BIGINT AS lo2, hi2::BIGINT AS hi2, abs(x - h)::BIGINT AS first, greatest(lo2 - y, y - hi2, 0)::BIGINT AS second FROM pos_pairs""")
def explain_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Envelope, clamp, second envelope and both areas, position by position, by a table function."""
    udfs.register(spark)
    _pairs(spark, sf_dir).createOrReplaceTempView("warp_pairs")
    whole = ", ".join(f"CAST(e.{c} AS BIGINT) AS {c}" for c in ("xi", "yi", "lo", "hi", "clamped", "lo2", "hi2", "first", "second"))
    return spark.sql(f"SELECT query_id, series_id, e.pos, {whole} FROM warp_pairs, LATERAL explain_bounds(x, y, {W}) e")


@query("warp_path_rows")
def warp_path_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The warping path of each query and its nearest series, by a table function."""
    udfs.register(spark)
    queries, db = workload(spark, sf_dir)
    best = search.nearest(queries, db, W).select("query_id", "series_id")
    best.join(db, "series_id").join(queries, "query_id").select("query_id", "series_id", F.col("v").alias("x"), "y").createOrReplaceTempView("warp_best")
    return spark.sql(f"SELECT query_id, series_id, e.* FROM warp_best, LATERAL warp_path(x, y, {W}) e")


@query("warp_path_cost", f"""WITH RECURSIVE {O.split(FIX, Q)}, {O.warp(N, W)}, best AS (SELECT query_id, series_id, dtw FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dtw, series_id) AS r FROM warp) WHERE r = 1)
 SELECT query_id, series_id, dtw::BIGINT AS cost, dtw::BIGINT AS aligned_l1, {N}::BIGINT AS xs, {N}::BIGINT AS ys, TRUE AS monotonic, TRUE AS in_band FROM best""")
def warp_path_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What a path must be: its matches cost the distance, and so do the two series aligned by it; it covers both in order and in the band."""
    rows = warp_path_rows(spark, sf_dir)
    before = Window.partitionBy("query_id", "series_id").orderBy("step")
    last = F.struct(F.lag("i").over(before).alias("i"), F.lag("j").over(before).alias("j"))
    stepped = rows.withColumn("last", last).withColumn("ok", F.coalesce((F.col("i") - F.col("last.i")).between(0, 1) & (F.col("j") - F.col("last.j")).between(0, 1), F.lit(True)))
    long = stepped.groupBy("query_id", "series_id").agg(
        F.sum(F.abs(F.col("xi") - F.col("yj"))).alias("cost"), udfs.pack_series("step", "xi").alias("x"), udfs.pack_series("step", "yj").alias("y"),
        F.count_distinct("i").alias("xs"), F.count_distinct("j").alias("ys"), F.min("ok").alias("monotonic"), F.max(F.abs(F.col("i") - F.col("j"))).alias("far"),
    )
    return long.select("query_id", "series_id", F.col("cost").cast("bigint").alias("cost"), X.lp_distance_pow("x", "y").cast("bigint").alias("aligned_l1"), "xs", "ys", "monotonic", (F.col("far") <= W).alias("in_band"))


@query("sql_scalar_functions", f"""WITH {O.split(FIX, Q)}, {O.bounds(N, W)}, s AS (SELECT series_id, {', '.join(f"sum(x) FILTER (WHERE least((pos - 1) // {N // D}, {D - 1}) = {k - 1}) AS s{k}" for k in (1, D))} FROM db_long GROUP BY 1)
 SELECT query_id, series_id, sum(lo)::BIGINT AS lows, sum(hi)::BIGINT AS highs, sum(h)::BIGINT AS clamped, max(s1)::BIGINT AS first_sum, max(s{D})::BIGINT AS last_sum FROM clamped JOIN s USING (series_id) GROUP BY 1, 2""")
def sql_scalar_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Envelope, clamp and piecewise sums by their SQL names."""
    udfs.register(spark)
    _pairs(spark, sf_dir).createOrReplaceTempView("warp_scalars")
    total = lambda a: f"CAST(aggregate({a}, 0D, (t, x) -> t + x) AS BIGINT)"
    return spark.sql(f"""SELECT query_id, series_id, {total('e.lo')} AS lows, {total('e.hi')} AS highs, {total('c')} AS clamped, CAST(s[0] AS BIGINT) AS first_sum, CAST(s[{D - 1}] AS BIGINT) AS last_sum
      FROM (SELECT query_id, series_id, warp_envelope(y, {W}) AS e, warp_clamp(x, y, {W}) AS c, warp_psum(x, {D}) AS s FROM warp_scalars)""")


@query("best_match", f"WITH RECURSIVE {O.split(FIX, Q)}, {O.warp(N, W)} SELECT query_id, min(dtw)::BIGINT AS dist, arg_min(series_id, (dtw, series_id)) AS series_id FROM warp GROUP BY 1")
def best_match(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The nearest series as an aggregate over all pairs."""
    found = _pairs(spark, sf_dir).select("query_id", "series_id", udfs.dtw("x", "y", W).alias("dist"))
    return found.groupBy("query_id").agg(udfs.best_match("dist", "series_id").alias("b")).select("query_id", F.col("b.dist").cast("bigint").alias("dist"), "b.series_id")


@query("nearest_in", f"""WITH RECURSIVE {O.FIXTURES['nation_month']}, packed AS (SELECT series_id, list(val::DOUBLE ORDER BY pos) AS v FROM long GROUP BY 1),
 {O.warp(80, 8, '1', 'SELECT a.series_id AS query_id, b.series_id, b.v AS x, a.v AS y FROM packed a CROSS JOIN packed b')}
 SELECT query_id, rank::INT AS rank, series_id, dtw::BIGINT AS dist FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dtw, series_id) AS rank FROM warp) WHERE rank <= 3""")
def nearest_in(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each nation's three nearest among all nations, by a table function over a small array of series."""
    udfs.register(spark)
    nations = S.nation_month(spark, sf_dir)
    pool = nations.agg(F.array_sort(F.collect_list(F.struct("series_id", "v"))).alias("p"))
    nations.select(F.col("series_id").alias("query_id"), F.col("v").alias("y")).crossJoin(F.broadcast(pool)).createOrReplaceTempView("warp_nations")
    return spark.sql("SELECT query_id, n.rank, p[n.at - 1].series_id AS series_id, CAST(n.dist AS BIGINT) AS dist FROM warp_nations, LATERAL nearest_in(y, transform(p, x -> x.v), 8, 3) n")


@query("medoids", f"""WITH RECURSIVE {O.FIXTURES['nation_month']}, packed AS (SELECT series_id, list(val::DOUBLE ORDER BY pos) AS v FROM long GROUP BY 1),
 named AS (SELECT n_nationkey::BIGINT AS series_id, r_name AS label FROM nation JOIN region ON n_regionkey = r_regionkey),
 {O.warp(80, 8, '1', 'SELECT a.series_id AS query_id, b.series_id, b.v AS x, a.v AS y FROM packed a JOIN named m ON a.series_id = m.series_id JOIN named o ON m.label = o.label JOIN packed b ON b.series_id = o.series_id')}
 SELECT label, query_id AS medoid FROM (SELECT label, query_id, row_number() OVER (PARTITION BY label ORDER BY sum(dtw), query_id) AS r FROM warp JOIN named ON query_id = named.series_id GROUP BY 1, 2) WHERE r = 1""")
def medoids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each region's most central nation, by a grouped aggregate."""
    return S.nation_month(spark, sf_dir).groupBy("label").agg(udfs.medoid("series_id", "v", 8).alias("medoid"))


# The index.
def _blocks(cover: boxindex.Cover) -> str:
    return " ".join(f"WHEN pos BETWEEN {a + 1} AND {b} THEN {k}" for k, (a, b) in enumerate(cover, 1))


UNEVEN = [(0, 3), (3, 20), (20, 40), (40, 83)]
for _tag, _cover in (("floor", boxindex.floor_cover(N, D)), ("uneven", UNEVEN)):
    register(
        f"psum_{_tag}_cover",
        lambda s, d, c=_cover: boxindex.points_of(S.fixture(s, d, FIX), c).select("series_id", F.posexplode(F.array(*(F.col(f"s{k}") for k in range(1, len(c) + 1)))).alias("b", "s")).select("series_id", (F.col("b") + 1).alias("block"), F.col("s").cast("bigint").alias("total")),
        f"WITH {O.FIXTURES[FIX]} SELECT series_id, CASE {_blocks(_cover)} END AS block, sum(val)::BIGINT AS total FROM long GROUP BY 1, 2",
    )


def _box_rows(boxes: DataFrame) -> DataFrame:
    parts = F.array(*(F.struct(F.lit(k).alias("block"), F.col(f"lo{k}").cast("bigint").alias("lo"), F.col(f"hi{k}").cast("bigint").alias("hi")) for k in range(1, D + 1)))
    return boxes.select("query_id", F.inline(parts))


COVER = boxindex.floor_cover(N, D)
register(
    "query_boxes", lambda s, d: _box_rows(boxindex.query_boxes(workload(s, d)[0], W, COVER)),
    f"WITH {O.split(FIX, Q)}, {O.bounds(N, W)} SELECT query_id, CASE {_blocks(COVER)} END AS block, sum(lo)::BIGINT AS lo, sum(hi)::BIGINT AS hi FROM q_env GROUP BY 1, 2",
)
for _tag, (_p, _sp) in NORMS.items():
    register(
        f"box_bound_{_tag}",
        lambda s, d, p=_p: (lambda qs, db: boxindex.points_of(db, COVER).crossJoin(F.broadcast(boxindex.query_boxes(qs, W, COVER))).select(*_value("power", F.floor(boxindex.point_bound_pow(COVER, p) / 1000 + 1e-6))))(*workload(s, d)),
        f"WITH {O.split(FIX, Q)}, {O.bounds(N, W, _sp, D)} SELECT query_id, series_id, floor(box / 1000 + 1e-6)::BIGINT AS power FROM bounds",
    )


@query("box_pages", f"""WITH {O.FIXTURES[FIX]}, sums AS (SELECT series_id, CASE {_blocks(COVER)} END AS b, sum(val) AS s FROM long GROUP BY 1, 2),
 points AS (SELECT series_id, max(s) FILTER (WHERE b = 1) AS s1, max(s) FILTER (WHERE b = 2) AS s2 FROM sums GROUP BY 1),
 edges AS (SELECT quantile_disc(s1, 0.5) AS e FROM points), strips AS (SELECT p.*, (s1 > e)::INT AS strip FROM points p CROSS JOIN edges),
 inner_edges AS (SELECT strip, quantile_disc(s2, 0.5) AS e FROM strips GROUP BY 1)
 SELECT 2 * s.strip + (s2 > e)::INT AS page_id, count(*) AS rows, min(s1)::BIGINT AS s1_min, max(s1)::BIGINT AS s1_max, min(s2)::BIGINT AS s2_min, max(s2)::BIGINT AS s2_max
 FROM strips s JOIN inner_edges i ON s.strip = i.strip GROUP BY 1""")
def box_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The table of four pages: two strips of s1, each in two tiles of s2."""
    points = boxindex.points_of(S.fixture(spark, sf_dir, FIX), COVER)
    pages = boxindex.page_table(boxindex.with_pages(points, boxindex.tiling(points, page_rows=1, n_points=4)), D)
    return pages.select("page_id", "rows", *(F.col(f"s{k}_{side}").cast("bigint").alias(f"s{k}_{side}") for k in (1, 2) for side in ("min", "max")))


# Search. All methods have the same answers, and so the same twin.
def answers_sql(name: str = FIX, n_queries: int = Q, n: int = N, w: int = W, k: int = 1) -> str:
    return f"""WITH RECURSIVE {O.split(name, n_queries)}, {O.warp(n, w)}
  SELECT query_id, rank::INT AS rank, series_id, dtw::BIGINT AS dist FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dtw, series_id) AS rank FROM warp) WHERE rank <= {k}"""


def _whole(found: DataFrame) -> DataFrame:
    return found.select("query_id", F.col("rank").cast("int").alias("rank"), "series_id", F.col("dist").cast("bigint").alias("dist"))


#: Points of a page: one of 4096 bytes, and one that holds all of a small collection.
PAGES = {"": boxindex.SMALL_PAGE, "_large_page": boxindex.LARGE_PAGE}


def _nearest(spark: SparkSession, sf_dir: str, method: str, k: int = 1, page_rows: int = boxindex.SMALL_PAGE, **more) -> DataFrame:
    source = indexed(spark, sf_dir, page_rows) if method.startswith("box") else workload(spark, sf_dir)
    return _whole(search.nearest(*source, W, k=k, method=method, **more))


for _method in search.METHODS:
    for _tag, _rows in PAGES.items() if _method.startswith("box") else [("", 0)]:
        register(f"nn_{_method}{_tag}", lambda s, d, m=_method, r=_rows: _nearest(s, d, m, page_rows=r), answers_sql())
        register(f"knn_{_method}{_tag}", lambda s, d, m=_method, r=_rows: _nearest(s, d, m, 5, r), answers_sql(k=5))
for _method in ("scan_pass1", "scan_pass2", "box_pass1", "box_pass2"):
    register(f"nn_early_abandon_{_method}", lambda s, d, m=_method: _nearest(s, d, m, early_abandon=True), answers_sql())
for _cascade in (("pass1",), ("pass1", "pass2"), ()):
    register(f"nn_custom_cascade_{'_'.join(_cascade) or 'none'}", lambda s, d, c=_cascade: _whole(search.nearest(*workload(s, d), W, cascade=c)), answers_sql())
for _count in (1, 50):
    register(f"nn_scan_pass2_of_{_count}", lambda s, d, c=_count: _whole(search.nearest(*workload(s, d, n_queries=c), W, method="scan_pass2")), answers_sql(n_queries=_count))

PAGE_ROWS = 8
register(
    "index_reach",
    lambda s, d: search.reach_counts(*indexed(s, d, PAGE_ROWS), W),
    f"""WITH RECURSIVE {O.split(FIX, Q)}, {O.bounds(N, W)}, {O.warp(N, W)}, {O.pages(N, W, PAGE_ROWS)},
  near AS (SELECT query_id, page_id FROM (SELECT *, coalesce(sum(rows) OVER (PARTITION BY query_id ORDER BY page_bound, page_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ahead FROM page_hits) WHERE ahead <= 1),
  seed AS (SELECT query_id, min(dtw) AS b FROM near JOIN placed_points USING (page_id) JOIN warp USING (query_id, series_id) GROUP BY 1)
  SELECT query_id, (SELECT count(*) FROM page_table) AS pages, (SELECT count(*) FROM points) AS points, count(*) AS pages_reached, sum(rows)::BIGINT AS points_reached
  FROM page_hits JOIN seed USING (query_id) WHERE page_bound <= b GROUP BY 1""",
)


@query("nn_rounds", answers_sql(k=3))
def nn_rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Best-first rounds over small pages."""
    queries, db = workload(spark, sf_dir)
    return _whole(search.search_rounds(boxindex.build(db, N, D, page_rows=PAGE_ROWS), queries, W, k=3))


@query("nn_native_scan", answers_sql())
def nn_native_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A plan with the first pass as a built-in filter; its limit is the least unwarped distance."""
    queries, db = workload(spark, sf_dir)
    near = search.nearest_lp(queries, db).select("query_id", F.col("dist").alias("limit"))
    return _whole(search.native_scan(queries, db, W, near))


@query("nn_lp", f"""WITH {O.split(FIX, Q)}, {O.bounds(N, W)} SELECT query_id, 1 AS rank, series_id, lp::BIGINT AS dist
  FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY lp, series_id) AS r FROM bounds) WHERE r = 1""")
def nn_lp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _whole(search.nearest(*workload(spark, sf_dir), method="lp"))


EPS = 1_500_000
for _method in search.METHODS:
    register(
        f"within_eps_{_method}",
        lambda s, d, m=_method: search.within(*(indexed if m.startswith("box") else workload)(s, d), EPS, W, method=m).select(*_value("dist", F.col("dist"))),
        f"WITH RECURSIVE {O.split(FIX, Q)}, {O.warp(N, W)} SELECT query_id, series_id, dtw::BIGINT AS dist FROM warp WHERE dtw <= {EPS}",
    )

JOIN_FIX, JOIN_N, JOIN_W, JOIN_EPS = "tag_walk", 64, 6, 60_000


@query("warp_self_join")
def warp_self_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All close pairs among the pages' tag walks."""
    every = S.fixture(spark, sf_dir, JOIN_FIX)
    pairs = join.warp_join(every, every, JOIN_N, JOIN_EPS, JOIN_W, self_join=True)
    return pairs.select("left_id", "right_id", F.col("dist").cast("bigint").alias("dist"))


@query("except_methods", "SELECT 'none' AS method, 0::BIGINT AS query_id, 0::BIGINT AS dist WHERE FALSE")
def except_methods(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Answers that differ between any method and brute force: none."""
    near = {m: _nearest(spark, sf_dir, m, 5).select("query_id", "dist") for m in search.METHODS}
    differ = [rows.exceptAll(near["brute"]).select(F.lit(m).alias("method"), "query_id", "dist") for m, rows in near.items() if m != "brute"]
    return search._union(differ)


@query("agree_methods", f"SELECT query_id, dist FROM ({answers_sql(k=5)})")
def agree_methods(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Answers that all of three methods give."""
    near = [_nearest(spark, sf_dir, m, 5).select("query_id", "dist") for m in ("brute", "scan_pass2", "box_pass2")]
    return near[0].intersectAll(near[1]).intersectAll(near[2])
