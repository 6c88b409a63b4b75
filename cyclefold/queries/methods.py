"""Queries of the method itself: every step, variant, baseline and measure, over whole tables."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.angles import TAU, normal
from ..operators import baselines, frames, gram, graph, homology, metrics, period, pyramid, spectral, vote, window
from ..operators import phase as phases
from ..plans import corrupt, storage, synth, workloads
from .registry import query, table

SIDE = 8
PERIOD, D, M, NEAR = 20.3712931847, 21, 24, 3.0  # no two windows have one phase
SIGMA = 6.0
START, HOURS, BUCKETS = "2024-01-01", 2, 360
SEASON = (80.0, 30.0)
K, T = 6, 14


# --- shared inputs ----------------------------------------------------------------------------


def emb_frames(spark: SparkSession, sf: str) -> DataFrame:
    return frames.from_table(table(spark, sf, "embeddings"), None, "vec_id", "embedding", (SIDE, SIDE, 1))


def emb_pairs(spark: SparkSession, sf: str) -> DataFrame:
    return gram.pair_distances(emb_frames(spark, sf))


def buckets(spark: SparkSession, sf: str) -> DataFrame:
    return frames.regular_series(table(spark, sf, "events"), "ts", "value", START, HOURS, BUCKETS)


def planted_series(spark: SparkSession, sf: str) -> DataFrame:
    return synth.season(frames.standardised(buckets(spark, sf)), 12.0, tuple(a / 20 for a in SEASON))


def linear_phase(spark: SparkSession, sf: str) -> tuple[DataFrame, int]:
    """The phase of windows of D frames if the table of vectors repeated every PERIOD rows."""
    e = table(spark, sf, "embeddings")
    n = e.count()
    i = F.col("vec_id").cast("int")
    rows = e.select(F.lit("0").alias("video_id"), i.alias("i"), F.pmod(F.lit(TAU) * F.col("vec_id") / F.lit(PERIOD), F.lit(TAU)).alias("phi"))
    return rows.filter(F.col("i") <= n - D), n


def emb_votes(spark: SparkSession, sf: str, near: float | None = None) -> DataFrame:
    phi, n = linear_phase(spark, sf)
    return vote.assign(phi, M, n / PERIOD, n, D, near)


PX = "px AS (SELECT vec_id AS t, generate_subscripts(embedding, 1) - 1 AS p, unnest(embedding)::DOUBLE AS val FROM embeddings)"
PAIRS = (
    "pairs AS (SELECT a.vec_id AS i, b.vec_id AS j, list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: (z[1]::DOUBLE - z[2]::DOUBLE)"
    " * (z[1]::DOUBLE - z[2]::DOUBLE))) AS d2 FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id)"
)
WPAIRS = PAIRS + f""", w0 AS (SELECT i, j, sum(d2) OVER (PARTITION BY j - i ORDER BY i ROWS BETWEEN CURRENT ROW AND {D - 1} FOLLOWING) AS d2,
  count(*) OVER (PARTITION BY j - i ORDER BY i ROWS BETWEEN CURRENT ROW AND {D - 1} FOLLOWING) AS c FROM pairs),
wpairs AS (SELECT i, j, d2 FROM w0 WHERE c = {D})"""
SERIES = f"""m AS (SELECT (epoch_us(ts) - epoch_us(TIMESTAMP '{START}')) // {HOURS * 3_600_000_000} AS t, count(*) AS n, avg(value) AS m FROM events GROUP BY 1),
s0 AS (SELECT g.t, coalesce(n, 0) AS n, coalesce(last_value(m IGNORE NULLS) OVER (ORDER BY g.t), first_value(m IGNORE NULLS) OVER (ORDER BY g.t ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)) AS v
  FROM (SELECT unnest(range({BUCKETS})) AS t) g LEFT JOIN m ON m.t = g.t)"""
PLANTED = (
    SERIES
    + f""", s AS (SELECT t, (v - avg(v) OVER ()) / stddev_pop(v) OVER () + {SEASON[0] / 20} * sin(2 * pi() * t / 12.0) + {SEASON[1] / 20} * sin(2 * (2 * pi() * t / 12.0)) AS v,
  2 * pi() * ((t % 12) / 12.0) AS phi FROM s0)"""
)
LAGS = (
    PLANTED
    + f""", c AS (SELECT t, v - avg(v) OVER () AS x, var_pop(v) OVER () AS var FROM s),
l AS (SELECT b.t - a.t AS lag, sum(a.x * b.x) AS r, sum(a.x * a.x + b.x * b.x) AS e, count(*) AS n, max(a.var) AS var FROM c a JOIN c b ON b.t > a.t AND b.t - a.t <= {BUCKETS // 2} GROUP BY 1)"""
)
PHI = f"n AS (SELECT count(*) AS n FROM embeddings), phi AS (SELECT vec_id AS i, {TAU} * vec_id / {PERIOD} - {TAU} * floor({TAU} * vec_id / {PERIOD} / {TAU}) AS phi FROM embeddings, n WHERE vec_id <= n - {D})"
VOTES = (
    PHI
    + f""", o AS (SELECT i, g.j, ({TAU} * g.j / {M} - phi) - {TAU} * floor(({TAU} * g.j / {M} - phi) / {TAU}) AS a FROM phi, (SELECT unnest(range({M})) AS j) g),
v AS (SELECT i, j, a * ({PERIOD} / {TAU}) AS s FROM o),
votes AS (SELECT j, i, i + floor(s)::BIGINT AS a, least(i + floor(s)::BIGINT + 1, i + {D - 1}) AS b, s - floor(s) AS frac, s AS "offset" FROM v WHERE s <= {D - 1})"""
)


def r(x: str) -> str:
    return f"round({x}, 6) + 0.0"


# --- frames and distances ---------------------------------------------------------------------


@query("frame_pixels", f"WITH {PX} SELECT t, p // 8 AS y, p % 8 AS x, {r('val')} AS val FROM px")
def frame_pixels(spark, sf):
    return frames.pixels(emb_frames(spark, sf)).select("t", "y", "x", "val")


@query("frame_rebuild", "SELECT vec_id AS t, true AS ok FROM embeddings")
def frame_rebuild(spark, sf):
    f = emb_frames(spark, sf)
    back = frames.rebuild(frames.pixels(f), SIDE).withColumnRenamed("px", "again")
    return f.join(back, ["video_id", "t"]).select("t", (F.col("px") == F.col("again")).alias("ok"))


TAPS = "taps AS (SELECT unnest([0, 1, 2, 3, 4]) AS tap, unnest([1, 4, 6, 4, 1]) / 16.0 AS wt)"


def halving(name: str, source: str, n: int) -> str:
    mirror = lambda k: f"least(abs(2 * {k} + {{0}}.tap - 2), {2 * (n - 1)} - abs(2 * {k} + {{0}}.tap - 2))"
    return f"""{name} AS (SELECT t, ky.k AS y, kx.k AS x, sum(val * a.wt * b.wt) AS val FROM {source} s
  JOIN (SELECT unnest(range({(n + 1) // 2})) AS k) ky ON true JOIN taps a ON s.y = {mirror('ky.k').format('a')}
  JOIN (SELECT unnest(range({(n + 1) // 2})) AS k) kx ON true JOIN taps b ON s.x = {mirror('kx.k').format('b')} GROUP BY t, ky.k, kx.k)"""


GRID = f"{PX}, {TAPS}, g AS (SELECT t, p // 8 AS y, p % 8 AS x, val FROM px), {halving('l2', 'g', 8)}"


@query("pyramid_layer2", f"WITH {GRID} SELECT t, y, x, {r('val')} AS val FROM l2")
def pyramid_layer2(spark, sf):
    return pyramid.reduce_relational(frames.pixels(emb_frames(spark, sf)), SIDE, SIDE).select("t", "y", "x", "val")


@query("pyramid_layer3", f"WITH {GRID}, {halving('l3', 'l2', 4)} SELECT t, y, x, {r('val')} AS val FROM l3")
def pyramid_layer3(spark, sf):
    half = pyramid.reduce_relational(frames.pixels(emb_frames(spark, sf)), SIDE, SIDE)
    return pyramid.reduce_relational(half, SIDE // 2, SIDE // 2).select("t", "y", "x", "val")


@query("pyramid_tile_kernel", "SELECT vec_id AS t, true AS close FROM embeddings")
def pyramid_tile_kernel(spark, sf):
    """The Arrow kernel's third layer agrees with the relational one."""
    kernel = frames.pixels(pyramid.reduce(emb_frames(spark, sf), 3)).select("t", "y", "x", F.col("val").alias("k"))
    both = kernel.join(pyramid_layer3(spark, sf), ["t", "y", "x"]).groupBy("t").agg(F.max(F.abs(F.col("k") - F.col("val"))).alias("far"), F.count("*").alias("n"))
    return both.select("t", ((F.col("far") < 1e-5) & (F.col("n") == 4)).alias("close"))


@query("frame_pair_distance", f"WITH {PAIRS} SELECT i, j, {r('d2')} AS d2 FROM pairs")
def frame_pair_distance(spark, sf):
    return emb_pairs(spark, sf).select("i", "j", "d2")


@query("frame_pair_distance_tiled", f"WITH {PAIRS} SELECT i, j, {r('d2')} AS d2 FROM pairs")
def frame_pair_distance_tiled(spark, sf):
    return gram.pair_distances(emb_frames(spark, sf), tile_px=32).select("i", "j", "d2")


@query(
    "gram_centered",
    f"""WITH {PAIRS}, f AS (SELECT i, j, d2 FROM pairs UNION ALL SELECT j, i, d2 FROM pairs UNION ALL SELECT vec_id, vec_id, 0 FROM embeddings),
m AS (SELECT i, avg(d2) AS m FROM f GROUP BY i), g AS (SELECT avg(d2) AS g FROM f)
SELECT f.i, f.j, {r('-0.5 * (d2 - a.m - b.m + g)')} AS g FROM f JOIN m a ON f.i = a.i JOIN m b ON f.j = b.i, g WHERE f.i <= f.j""",
)
def gram_centered(spark, sf):
    return gram.centred_of_frames(emb_frames(spark, sf)).select("i", "j", "g")


@query("projection_isometry", "SELECT 0.0::DOUBLE AS max_err")
def projection_isometry(spark, sf):
    """The largest relative error of a distance after the projection."""
    f = emb_frames(spark, sf)
    return gram.distance_error(f, gram.isometric(f)).agg(F.max("err").alias("max_err"))


@query(
    "sketch_distance",
    f"""WITH {PX}, k AS (SELECT t, val, md5(concat_ws('|', '42', (p // 8)::VARCHAR, (p % 8)::VARCHAR, '0')) AS h FROM px),
c AS (SELECT t, ('0x' || substr(h, 1, 8))::BIGINT % 16 AS k, sum(CASE WHEN ('0x' || substr(h, 9, 1))::BIGINT < 8 THEN val ELSE -val END) AS v FROM k GROUP BY ALL)
SELECT a.t AS i, b.t AS j, {r('sum((a.v - b.v) * (a.v - b.v))')} AS d2 FROM c a JOIN c b ON a.k = b.k AND a.t < b.t GROUP BY ALL""",
)
def sketch_distance(spark, sf):
    z = gram.sketch(frames.pixels(emb_frames(spark, sf)), 16).select("video_id", "t", F.lit(1).alias("h"), F.lit(16).alias("w"), F.lit(1).alias("ch"), F.col("z").alias("px"))
    return gram.pair_distances(z.withColumn("px", F.col("px").cast("array<double>"))).select("i", "j", "d2")


@query(
    "knn_graph",
    f"""WITH {PAIRS}, f AS (SELECT i, j, d2 FROM pairs UNION ALL SELECT j, i, d2 FROM pairs),
k AS (SELECT i, j, row_number() OVER (PARTITION BY i ORDER BY d2, j) AS rnk, d2 FROM f) SELECT i, j, rnk, {r('d2')} AS d2 FROM k WHERE rnk <= 8""",
)
def knn_graph(spark, sf):
    return gram.nearest_frames(emb_frames(spark, sf), 8).select("i", "j", "rnk", "d2")


@query("isomap_surrogate", "SELECT vec_id AS t, 0.0::DOUBLE AS resid FROM embeddings")
def isomap_surrogate(spark, sf):
    """The surrogate is a mode of the centred geodesic distances: what the matrix makes of it, less its own
    multiple, is zero in every frame. Geodesics are the table form, which ``geodesic_hops`` holds against SQL."""
    f = emb_frames(spark, sf)
    graphs = period.neighbour_graphs(f)
    y = storage.materialise(period.isomap1d_of_frames(f, graphs=graphs).select("t", "y"))
    ends = F.explode(F.array(F.struct("i", "j"), F.struct(F.col("j").alias("i"), F.col("i").alias("j")))).alias("e")
    g2 = period.geodesics_of_frames(f, graphs=graphs).select(ends, (F.col("dist") * F.col("dist")).alias("g2")).select("e.i", "e.j", "g2")
    n, size = y.count(), y.agg(F.sum(F.col("y") * F.col("y"))).first()[0]
    # the centring turns into sums, as y sums to zero: (B y)_i = -1/2 (sum_j g2_ij y_j - sum_j m_j y_j)
    own = g2.join(F.broadcast(y.withColumnRenamed("t", "j")), "j").groupBy("i").agg((F.sum("g2") / n).alias("m"), F.sum(F.col("g2") * F.col("y")).alias("s"))
    both = storage.materialise(own.join(y.withColumnRenamed("t", "i"), "i"))
    flat = both.agg(F.sum(F.col("m") * F.col("y"))).first()[0]
    return both.select(F.col("i").alias("t"), ((-0.5 * (F.col("s") - flat) - size * F.col("y")) / size).alias("resid"))


@query("isomap_landmarks", "SELECT marks, true AS same_period FROM (SELECT unnest([40, 80, 160]) AS marks)")
def isomap_landmarks(spark, sf):
    """Geodesics from a few frames only give the period that all frames give."""
    g = workloads.grid(spark, "noise", [0.1], (1,), (20,))
    m = storage.materialise(gram.distance_matrices(pyramid.reduce(synth.planted(spark, table(spark, sf, "embeddings"), g, 400, 32, 32, 3), 3)))
    out = []
    for marks in (40, 80, 160):
        y = period.isomap1d(m, landmarks=marks).select(F.lit("a").alias("series_id"), "t", F.col("y").alias("v"))
        out.append(period.estimate(y).select(F.lit(marks).alias("marks"), (F.abs(F.col("T") - 20) < 0.2).alias("same_period")))
    return workloads.union(out)


# --- series and periods -----------------------------------------------------------------------


@query("series_2h", f"WITH {SERIES} SELECT t, n, round(v, 9) + 0.0 AS v FROM s0", digits=9)
def series_2h(spark, sf):
    return buckets(spark, sf)


@query("series_planted", f"WITH {PLANTED} SELECT t, {r('v')} AS x, {r('phi')} AS phi FROM s")
def series_planted(spark, sf):
    return planted_series(spark, sf).select("t", F.col("v").alias("x"), "phi")


def lag_values(spark, sf, method):
    return period.lag_values(planted_series(spark, sf).select("t", "v"), BUCKETS // 2, method)


@query("acf_all_lags", f"WITH {LAGS} SELECT lag, {r('r / n / var')} AS val FROM l")
def acf_all_lags(spark, sf):
    return lag_values(spark, sf, "acf")


@query("nsdf_all_lags", f"WITH {LAGS} SELECT lag, {r('2 * r / e')} AS val FROM l")
def nsdf_all_lags(spark, sf):
    return lag_values(spark, sf, "nsdf")


YIN = "1 - (e - 2 * r) / n / avg((e - 2 * r) / n) OVER (ORDER BY lag)"


@query("yin_all_lags", f"WITH {LAGS} SELECT lag, {r(YIN)} AS val FROM l")
def yin_all_lags(spark, sf):
    return lag_values(spark, sf, "yin")


def first_key_maximum(values: str, by: str = "") -> str:
    part = f"PARTITION BY {by}" if by else ""
    out = f"{by}, " if by else ""
    return f"""x AS (SELECT {out}lag, val, lag(val) OVER ({part} ORDER BY lag) AS a, lead(val) OVER ({part} ORDER BY lag) AS c,
  min(CASE WHEN val <= 0 THEN lag END) OVER ({part}) AS z FROM {values}),
y AS (SELECT *, max(val) OVER ({part}) AS top FROM x WHERE lag >= greatest(3, coalesce(z, 3)) AND val >= a AND val > c AND val > 0)"""


@query("period_argmax", f"WITH {LAGS}, acf AS (SELECT lag, r / n / var AS val FROM l), {first_key_maximum('acf')} SELECT 'events' AS series, min(lag) AS T FROM y WHERE val >= 0.8 * top")
def period_argmax(spark, sf):
    return period.first_key_maximum(lag_values(spark, sf, "acf")).select(F.lit("events").alias("series"), "T")


def peaks(value: str, method: str) -> str:
    return f"""SELECT * FROM (WITH {LAGS}, v AS (SELECT lag, {value} AS val FROM l), {first_key_maximum('v')}
SELECT 'events' AS series_id, round(lag + 0.5 * (a - c) / (a - 2 * val + c), 6) + 0.0 AS T, round(val, 6) + 0.0 AS confidence, '{method}' AS method FROM y WHERE val >= 0.8 * top ORDER BY lag LIMIT 1)"""


@query("period_estimate", " UNION ALL ".join([peaks("r / n / var", "acf"), peaks("2 * r / e", "nsdf"), peaks(YIN, "yin")]))
def period_estimate(spark, sf):
    s = planted_series(spark, sf).select(F.lit("events").alias("series_id"), "t", "v")
    out = None
    for method in ("acf", "nsdf", "yin"):
        one = period.estimate(s, method).withColumn("method", F.lit(method))
        out = one if out is None else out.unionByName(one)
    return out


LONGEST = 28


def daily(rows, by, day, value):
    """(by), t, v: daily sums of a value over all days, gaps as zero, with a weekly season of three
    standard deviations on top."""
    first, last = rows.agg(F.min(day), F.max(day)).first()
    if first is None:
        return rows.select(*by, F.lit(0).alias("t"), F.lit(0.0).alias("v")).limit(0)
    t = F.datediff(day, F.lit(first)).cast("int")
    sums = rows.groupBy(*by, t.alias("t")).agg(F.sum(value).alias("q"))
    grid = (rows.select(*by).distinct() if by else rows.sparkSession.range(1)).select(*by, F.explode(F.sequence(F.lit(0), F.lit((last - first).days))).alias("t"))
    whole = grid.join(sums, [*by, "t"], "left").withColumn("q", F.coalesce("q", F.lit(0.0)))
    scale = F.stddev_pop("q").over(window.Window.partitionBy(*(by or [F.lit(0)])))
    return whole.select(*by, "t", (F.col("q") + 3 * scale * F.sin(F.lit(TAU) * F.col("t") / 7)).alias("v"))


def daily_sql(rows: str, by: str) -> str:
    """CTEs up to acf (by, lag, val) from a CTE ``rows`` (by, day, q)."""
    c, on = (f"{by}, ", f"a.{by} = b.{by} AND ") if by else ("", "")
    part = f"PARTITION BY {by}" if by else ""
    grid = f"(SELECT DISTINCT {by} FROM rows) g CROSS JOIN" if by else ""
    match = f"q.{by} = g.{by} AND " if by else ""
    return f"""rows AS ({rows}), lim AS (SELECT min(day) AS lo, max(day) AS hi FROM rows), q AS (SELECT {c}date_diff('day', lo, day) AS t, sum(q) AS q FROM rows, lim GROUP BY ALL),
f AS (SELECT {f'g.{by}, ' if by else ''}d.t, coalesce(q.q, 0) AS q FROM {grid} (SELECT unnest(range(date_diff('day', lo, hi) + 1)) AS t FROM lim) d LEFT JOIN q ON {match}q.t = d.t),
s AS (SELECT {c}t, q + 3 * stddev_pop(q) OVER ({part}) * sin({TAU} * t / 7) AS v FROM f),
c AS (SELECT {c}t, v - avg(v) OVER ({part}) AS x, var_pop(v) OVER ({part}) AS var FROM s),
acf AS (SELECT {f'a.{by}, ' if by else ''}b.t - a.t AS lag, sum(a.x * b.x) / count(*) / max(a.var) AS val FROM c a JOIN c b ON {on}b.t > a.t AND b.t - a.t <= {LONGEST} GROUP BY ALL)"""


@query(
    "period_by_brand",
    f"""WITH {daily_sql("SELECT p_brand, l_shipdate::DATE AS day, l_quantity AS q FROM lineitem JOIN part ON l_partkey = p_partkey", "p_brand")},
{first_key_maximum('acf', 'p_brand')} SELECT p_brand, min(lag) AS T FROM y WHERE val >= 0.8 * top GROUP BY p_brand""",
)
def period_by_brand(spark, sf):
    """One series a brand, all at once: the many-series regime."""
    li = table(spark, sf, "lineitem").select(F.col("l_partkey").alias("p_partkey"), "l_quantity", F.col("l_shipdate").cast("date").alias("day"))
    rows = li.join(table(spark, sf, "part").select("p_partkey", "p_brand"), "p_partkey")
    return period.first_key_maximum(period.lag_values(daily(rows, ["p_brand"], "day", "l_quantity"), LONGEST, "acf", ["p_brand"]), by=["p_brand"])


@query("period_of_orders", f"WITH {daily_sql('SELECT o_orderdate::DATE AS day, o_totalprice AS q FROM orders', '')}, {first_key_maximum('acf')} SELECT min(lag) AS T FROM y WHERE val >= 0.8 * top")
def period_of_orders(spark, sf):
    """One long daily series."""
    rows = table(spark, sf, "orders").select(F.col("o_orderdate").cast("date").alias("day"), "o_totalprice")
    return period.first_key_maximum(period.lag_values(daily(rows, [], "day", "o_totalprice"), LONGEST))


# --- windows and graphs -----------------------------------------------------------------------


@query("window_stack", f"WITH {SERIES} SELECT a.t AS i, g.k, round(b.v, 9) + 0.0 AS v FROM s0 a, (SELECT unnest(range(13)) AS k) g JOIN s0 b ON b.t = a.t + g.k WHERE a.t <= {BUCKETS - 13}", digits=9)
def window_stack(spark, sf):
    return window.stack(buckets(spark, sf), 13).select("i", F.posexplode("w").alias("k", "v"))


@query("window_distance", f"WITH {WPAIRS} SELECT i, j, {r('d2')} AS d2 FROM wpairs")
def window_distance(spark, sf):
    return wpairs(spark, sf).select("i", "j", "d2")


@query("window_distance_d1", f"WITH {PAIRS} SELECT i, j, {r('d2')} AS d2 FROM pairs")
def window_distance_d1(spark, sf):
    return wpairs(spark, sf, 1).select("i", "j", "d2")


@query("window_length_rule", "SELECT T::DOUBLE AS T, c, (round(T * c) + 1)::BIGINT AS d, (round(T * c) + 1) >= 4 AS enough FROM (SELECT unnest([3.0, 6.13, 12.0, 19.6, 200.0]) AS T) a CROSS JOIN (SELECT unnest([1, 2, 3]) AS c) b")
def window_length_rule(spark, sf):
    periods = spark.createDataFrame([(t,) for t in (3.0, 6.13, 12.0, 19.6, 200.0)], "T double")
    both = periods.withColumn("c", F.explode(F.array(F.lit(1), F.lit(2), F.lit(3))))
    return both.withColumn("d", window.length(F.col("T"), F.col("c"))).withColumn("enough", window.check_dimension(F.col("d"), F.lit(2)))


def wpairs(spark, sf, d=D):
    return gram.window_pair_distances(emb_frames(spark, sf), d)


STEP = "(SELECT i, j, 1.0 AS w FROM wpairs WHERE d2 <= (SELECT quantile_cont(d2, 0.1) FROM wpairs))"
GAUSS = f"(SELECT i, j, exp(-d2 / (2 * {SIGMA * SIGMA})) AS w FROM wpairs)"
PRINTED = f"(SELECT i, j, exp(-sqrt(d2) / (2 * {SIGMA * SIGMA})) AS w FROM wpairs)"


@query("adjacency_step", f"WITH {WPAIRS} SELECT i, j, {r('w')} AS w FROM {STEP}")
def adjacency_step(spark, sf):
    """Windows nearer than nine tenths of all pairs are linked."""
    near = gram.window_quantile(emb_frames(spark, sf), D, 0.1) or 0.0
    sigma = math.sqrt(near)
    if sigma * sigma < near:  # the pair at the quantile is one of them
        sigma = math.nextafter(sigma, math.inf)
    return graph.adjacency(wpairs(spark, sf), sigma, "step").select("i", "j", "w")


@query("adjacency_gauss", f"WITH {WPAIRS} SELECT i, j, {r('w')} AS w FROM {GAUSS}")
def adjacency_gauss(spark, sf):
    return graph.adjacency(wpairs(spark, sf), SIGMA).select("i", "j", "w")


@query("adjacency_printed", f"WITH {WPAIRS} SELECT i, j, {r('w')} AS w FROM {PRINTED}")
def adjacency_printed(spark, sf):
    return graph.adjacency(wpairs(spark, sf), SIGMA, "printed").select("i", "j", "w")


BOTH = f"{WPAIRS}, e AS {GAUSS}, b AS (SELECT i, j, w FROM e UNION ALL SELECT j, i, w FROM e)"


@query("degree_vector", f"WITH {BOTH} SELECT i, {r('sum(w)')} AS deg FROM b GROUP BY i")
def degree_vector(spark, sf):
    return graph.degree(graph.adjacency(wpairs(spark, sf), SIGMA)).select("i", "deg")


@query("laplacian_coo", f"WITH {BOTH} SELECT i, i AS j, {r('sum(w)')} AS val FROM b GROUP BY i UNION ALL SELECT i, j, {r('-w')} FROM b")
def laplacian_coo(spark, sf):
    return graph.laplacian(graph.adjacency(wpairs(spark, sf), SIGMA)).select("i", "j", "val")


@query("laplacian_rowsum", f"SELECT vec_id AS i, 0.0::DOUBLE AS s FROM embeddings WHERE vec_id <= (SELECT count(*) FROM embeddings) - {D}")
def laplacian_rowsum(spark, sf):
    return graph.laplacian(graph.adjacency(wpairs(spark, sf), SIGMA)).groupBy("i").agg(F.sum("val").alias("s"))


# --- the ideal model --------------------------------------------------------------------------

N = K * T
LAMBDA = '"lambda"'
IDEAL = f"""g AS (SELECT unnest(range({N})) AS i), d AS (SELECT DISTINCT ((l * {T} + s) % {N} + {N}) % {N} AS o FROM (SELECT unnest(range({K})) AS l) a, (SELECT unnest([-1, 0, 1]) AS s) b),
lap AS (SELECT i, (i + o) % {N} AS j, CASE WHEN o = 0 THEN {3 * K - 1}.0 ELSE -1.0 END AS val FROM g, d)"""
SPECTRUM = f"sp AS (SELECT m, CASE WHEN m % {K} = 0 THEN {3 * K} - {K} * (1 + 2 * cos({TAU} * m / {N})) ELSE {3.0 * K} END AS {LAMBDA} FROM (SELECT unnest(range(1, {N // 2 + 1})) AS m))"


def customer_windows(spark, sf):
    """Every ``N`` customers of the table stand for the windows of an ideal recording: video_id, i."""
    key = F.col("c_custkey")
    return table(spark, sf, "customer").select(F.floor(key / N).alias("video_id"), F.pmod(key, F.lit(N)).cast("int").alias("i"))


def customer_entries(spark, sf, k, T):
    """The ideal Laplacian's rows of these windows."""
    return customer_windows(spark, sf).join(F.broadcast(spectral.ideal_laplacian(spark, k, T)), "i").select("video_id", "i", "j", "val")


RECORDINGS = f"rec AS (SELECT DISTINCT c_custkey // {N} AS video_id FROM customer)"


@query("ideal_laplacian", f"WITH {IDEAL} SELECT c_custkey // {N} AS video_id, i, j, val::DOUBLE AS val FROM customer JOIN lap ON lap.i = c_custkey % {N}")
def ideal_laplacian(spark, sf):
    return customer_entries(spark, sf, K, T)


@query("ideal_spectrum", f'WITH {SPECTRUM}, {RECORDINGS} SELECT video_id, m, {r(LAMBDA)} AS {LAMBDA} FROM rec, sp')
def ideal_spectrum(spark, sf):
    """The spectrum of each recording from its windows' rows; the SQL has the closed form."""
    return spectral.circulant_spectrum(customer_entries(spark, sf, K, T), N)


@query("ideal_residual", f"WITH {SPECTRUM}, {RECORDINGS} SELECT video_id, m, 0.0::DOUBLE AS resid FROM rec, sp")
def ideal_residual(spark, sf):
    return spectral.ideal_residual(customer_entries(spark, sf, K, T), K, T)


@query(
    "ideal_numeric_modes",
    f"""WITH {SPECTRUM}, {RECORDINGS}, a AS (SELECT {LAMBDA} FROM sp UNION ALL SELECT {LAMBDA} FROM sp WHERE m < {N // 2}),
o AS (SELECT row_number() OVER (ORDER BY {LAMBDA}) AS rank, {LAMBDA} FROM a) SELECT video_id, rank, {r(LAMBDA)} AS {LAMBDA} FROM rec, o""",
)
def ideal_numeric_modes(spark, sf):
    entries = spectral.circulant(customer_entries(spark, sf, K, T), N).withColumn("video_id", F.col("video_id").cast("string"))
    return spectral.low_modes(entries, N).select(F.col("video_id").cast("long").alias("video_id"), "rank", "lambda")


@query(
    "zero_crossings",
    f"""WITH v AS (SELECT m, t, round(cos({TAU} * m * (t + 0.25) / {N}), 9) AS v FROM (SELECT unnest(range(1, {N // 2})) AS m) a, (SELECT unnest(range({N})) AS t) b),
s AS (SELECT m, t, last_value(CASE WHEN v <> 0 THEN sign(v) END IGNORE NULLS) OVER (PARTITION BY m ORDER BY t) AS s FROM v),
c AS (SELECT m, s <> lag(s) OVER (PARTITION BY m ORDER BY t) AS c FROM s) SELECT m, count(*) FILTER (WHERE c) AS zc FROM c GROUP BY m""",
)
def zero_crossings(spark, sf):
    m = spark.range(1, N // 2).select(F.col("id").cast("int").alias("m"), F.explode(F.sequence(F.lit(0), F.lit(N - 1))).alias("t"))
    modes = m.withColumn("v", F.round(F.cos(F.lit(TAU) * F.col("m") * (F.col("t") + 0.25) / N), 9))
    return phases.zero_crossings(modes, ["m"])


@query(
    "mode_pair_choice",
    """WITH c AS (SELECT user_id AS video_id, event_type, count(*) AS n FROM events GROUP BY ALL), o AS (SELECT *, row_number() OVER w AS rank, lead(n) OVER w AS n2 FROM c WINDOW w AS (PARTITION BY video_id ORDER BY event_type)),
p AS (SELECT *, greatest(n, n2) <= 1.2::DOUBLE * least(n, n2) AS good FROM o WHERE n2 IS NOT NULL),
b AS (SELECT video_id, min(rank) AS first, arg_min(rank, (n + n2) * 1000 + rank) FILTER (WHERE good) AS best FROM p GROUP BY video_id)
SELECT video_id, coalesce(best, first) AS lo, coalesce(best, first) + 1 AS hi, best IS NULL AS fallback FROM b""",
)
def mode_pair_choice(spark, sf):
    """A user's kinds of events in order are the modes, how often they occur the crossings."""
    counts = table(spark, sf, "events").groupBy(F.col("user_id").alias("video_id"), "event_type").agg(F.count("*").alias("zero_cross"))
    rank = F.row_number().over(window.Window.partitionBy("video_id").orderBy("event_type"))
    return phases.mode_pair(counts.select("video_id", rank.alias("rank"), "zero_cross"), by=["video_id"])


ATAN = f"atan2(cos({TAU} * value / {T} + 0.3), sin({TAU} * value / {T} + 0.3))"


def swaying_phase(spark, sf):
    """Every ``N`` events of the table are a recording; their values sway its even turning a little."""
    i = F.pmod("event_id", F.lit(N))
    angle = F.lit(TAU) * i / T + 0.3 + 0.0001 * F.col("value")
    rows = table(spark, sf, "events").select(F.floor(F.col("event_id") / N).alias("video_id"), i.cast("int").alias("i"), angle.alias("a"))
    return rows.select("video_id", "i", F.pmod(F.atan2(F.cos("a"), F.sin("a")), F.lit(TAU)).alias("phi"))


@query("phase_atan2", f"SELECT event_id AS n, {r(f'({ATAN} + {TAU}) % {TAU}')} AS phi FROM events")
def phase_atan2(spark, sf):
    """The values of the events turn once every ``T``."""
    angle = F.lit(TAU) * F.col("value") / T + 0.3
    return table(spark, sf, "events").select(F.col("event_id").alias("n"), F.pmod(F.atan2(F.cos(angle), F.sin(angle)), F.lit(TAU)).alias("phi"))


@query(
    "phase_unwrap",
    f"""WITH a AS (SELECT event_id // {N} AS video_id, event_id % {N} AS i, {TAU} * (event_id % {N}) / {T} + 0.0001 * value AS a FROM events)
SELECT video_id, i, {r('a - first_value(a) OVER (PARTITION BY video_id ORDER BY i)')} AS phi_u FROM a""",
)
def phase_unwrap(spark, sf):
    return phases.unwrap(swaying_phase(spark, sf)).select("video_id", "i", "phi_u")


def counted(spark, sf, how):
    """Every 280 events of the table are the windows of a recording of 300 frames."""
    i = F.pmod("event_id", F.lit(280))
    video = F.floor(F.col("event_id") / 280).alias("video_id")
    phi = table(spark, sf, "events").select(video, i.cast("int").alias("i"), F.pmod(F.lit(TAU) * i / 20, F.lit(TAU)).alias("phi"))
    return phases.cycle_count(phases.unwrap(phi), 300, 21, how).select("video_id", "k")


@query("cycle_count_printed", f"SELECT event_id // 280 AS video_id, {r('300 * ((max(event_id) - min(event_id)) / 20.0) / 280')} AS k FROM events GROUP BY 1")
def cycle_count_printed(spark, sf):
    return counted(spark, sf, "printed")


@query("cycle_count_slope", "SELECT event_id // 280 AS video_id, CASE WHEN count(*) > 1 THEN 15.0::DOUBLE END AS k FROM events GROUP BY 1")
def cycle_count_slope(spark, sf):
    return counted(spark, sf, "slope")


# --- votes and templates ----------------------------------------------------------------------


@query(
    "coverage_interval",
    f"WITH {PHI}, c AS (SELECT i, phi, phi + {TAU} * (n / {PERIOD}) * {D} / n AS e FROM phi, n) SELECT i, {r('phi')} AS lo, {r(f'e - {TAU} * floor(e / {TAU})')} AS hi, e >= {TAU} AS wraps FROM c",
)
def coverage_interval(spark, sf):
    phi, n = linear_phase(spark, sf)
    return vote.coverage(phi, n / PERIOD, n, D).select("i", "lo", "hi", "wraps")


@query("vote_assign", f"WITH {VOTES} SELECT j, i, a, b, {r('frac')} AS frac FROM votes")
def vote_assign(spark, sf):
    return emb_votes(spark, sf).select("j", "i", "a", "b", "frac")


@query("vote_assign_f", f'WITH {VOTES} SELECT j, i, a, b, {r("frac")} AS frac FROM votes WHERE abs("offset") <= {NEAR}')
def vote_assign_f(spark, sf):
    return emb_votes(spark, sf, NEAR).select("j", "i", "a", "b", "frac")


@query("vote_stats", f"WITH {VOTES} SELECT j, count(*) AS votes, count(DISTINCT a) AS frames FROM votes GROUP BY j")
def vote_stats(spark, sf):
    return vote.stats(emb_votes(spark, sf)).select("j", "votes", "frames")


MEDIAN = f"""{VOTES}, {PX}, near AS (SELECT * FROM votes WHERE abs("offset") <= {NEAR}),
med AS (SELECT j, pa.p, median((1 - frac) * pa.val + frac * pb.val) AS val, count(*) AS n_votes FROM near JOIN px pa ON pa.t = a JOIN px pb ON pb.t = b AND pb.p = pa.p GROUP BY j, pa.p)"""
TEMPLATE = f"WITH {MEDIAN} SELECT j, p // 8 AS y, p % 8 AS x, round(val, 5) + 0.0 AS val, n_votes FROM med"


@query("template_median", TEMPLATE)
def template_median(spark, sf):
    out = vote.median_relational(emb_votes(spark, sf, NEAR), frames.pixels(emb_frames(spark, sf)))
    return out.select("j", "y", "x", F.round("val", 5).alias("val"), "n_votes")


def tile_template(spark, sf, median="exact"):
    out = vote.median_template(emb_votes(spark, sf, NEAR), frames.tiles(emb_frames(spark, sf), 16), M, median)
    long = out.select("j", "tile", "n_votes", F.posexplode("px").alias("q", "val")).withColumn("p", F.col("tile") * 16 + F.col("q"))
    return long.select("j", "p", F.col("val").cast("double").alias("val"), "n_votes")


@query("template_median_tile", TEMPLATE)
def template_median_tile(spark, sf):
    t = tile_template(spark, sf)
    return t.select("j", F.floor(F.col("p") / 8).alias("y"), F.pmod("p", F.lit(8)).alias("x"), F.round("val", 5).alias("val"), "n_votes")


@query("template_hist_median", f"WITH {MEDIAN} SELECT j, p, true AS close FROM med")
def template_hist_median(spark, sf):
    """Each histogram median lies within one bin of the exact one."""
    rough = tile_template(spark, sf, "hist").withColumnRenamed("val", "rough")
    return tile_template(spark, sf).join(rough, ["j", "p"]).select("j", "p", (F.abs(F.col("val") - F.col("rough")) <= 2 / 256).alias("close"))


@query("template_approx_median", f"SELECT j, y, x, true AS close FROM (SELECT unnest(range({M})) AS j), (SELECT unnest(range({SIDE})) AS y), (SELECT unnest(range({SIDE})) AS x)")
def template_approx_median(spark, sf):
    """Approximate medians lie between the exact percentiles on either side of the median."""
    votes, px = emb_votes(spark, sf, NEAR), frames.pixels(emb_frames(spark, sf))
    at = lambda c, v: px.select(F.col("t").alias(c), "y", "x", F.col("val").alias(v))
    blend = votes.join(at("a", "va"), "a").join(at("b", "vb"), ["b", "y", "x"])
    value = (1 - F.col("frac")) * F.col("va") + F.col("frac") * F.col("vb")
    both = blend.groupBy("j", "y", "x").agg(F.percentile_approx(value, 0.5, 1000).alias("val"), F.percentile(value, [0.45, 0.55]).alias("p"))
    return both.select("j", "y", "x", F.col("val").between(F.col("p")[0], F.col("p")[1]).alias("close"))


SORTED = f"WITH {PHI} SELECT row_number() OVER (ORDER BY phi, i) - 1 AS pos, i AS t FROM phi"


@query("template_simple", SORTED)
def template_simple(spark, sf):
    return baselines.sort_by_phase(linear_phase(spark, sf)[0]).select("pos", "t")


@query("template_mean_fold", f"WITH {PLANTED} SELECT floor((t % 12) / 0.5)::BIGINT AS bin, {r('avg(v)')} AS mean, {r('median(v)')} AS med, count(*) AS n FROM s GROUP BY 1")
def template_mean_fold(spark, sf):
    return baselines.fold_known_period(planted_series(spark, sf), 12.0, 24)


SEAM = "(SELECT sum((a.val - b.val) * (a.val - b.val)) / max(a.n) AS e FROM {x} a JOIN {x} b ON b.p = a.p AND b.pos = (a.pos + 1) % a.n)"


@query(
    "seam_energy",
    f"""WITH {MEDIAN}, input AS (SELECT t AS pos, p, val, n FROM px, n),
ordered AS (SELECT row_number() OVER (ORDER BY phi, i) - 1 AS pos, i AS t FROM phi), simple AS (SELECT pos, p, val, n - {D - 1} AS n FROM ordered JOIN px USING (t), n),
middle AS (SELECT j AS pos, p, val, {M} AS n FROM med)
SELECT 'input' AS kind, {r('e')} AS e FROM {SEAM.format(x='input')} UNION ALL SELECT 'simple', {r('e')} FROM {SEAM.format(x='simple')} UNION ALL SELECT 'median', round(e, 5) + 0.0 FROM {SEAM.format(x='middle')}""",
)
def seam_energy(spark, sf):
    f = emb_frames(spark, sf).select("t", "px")
    given = f.select(F.lit("input").alias("kind"), F.col("t").alias("pos"), "px")
    order = baselines.sort_by_phase(linear_phase(spark, sf)[0])
    simple = order.join(f, "t").select(F.lit("simple").alias("kind"), "pos", "px")
    tiles = vote.median_template(emb_votes(spark, sf, NEAR), frames.tiles(emb_frames(spark, sf), 64), M)
    middle = tiles.select(F.lit("median").alias("kind"), F.col("j").alias("pos"), "px")
    out = metrics.seam_energy(given.unionByName(simple).unionByName(middle), ["kind"])
    return out.withColumn("e", F.when(F.col("kind") == "median", F.round("e", 5)).otherwise(F.col("e")))


@query(
    "angular_error",
    f"""WITH {PLANTED}, p AS (SELECT t, (phi + 0.2 * sin(phi) + 1.0 + 0.01 * v) - {TAU} * floor((phi + 0.2 * sin(phi) + 1.0 + 0.01 * v) / {TAU}) AS phi, phi AS truth FROM s),
b AS (SELECT d, d * phi - truth AS e FROM p, (SELECT unnest([1, -1]) AS d)), o AS (SELECT d, atan2(avg(sin(e)), avg(cos(e))) AS o FROM b GROUP BY d),
w AS (SELECT d, (e - o) - {TAU} * floor((e - o + {math.pi}) / {TAU}) AS w FROM b JOIN o USING (d)),
x AS (SELECT d, degrees(avg(abs(w))) AS err FROM w GROUP BY d) SELECT {r('min(err)')} AS err_deg FROM x""",
)
def angular_error(spark, sf):
    s = planted_series(spark, sf).withColumn("video_id", F.lit("0"))
    bent = s.select("video_id", F.col("t").alias("i"), F.pmod(F.col("phi") + 0.2 * F.sin("phi") + 1.0 + 0.01 * F.col("v"), F.lit(TAU)).alias("phi"))
    return metrics.angular_error(bent, s.select("video_id", "t", "phi")).select("err_deg")


@query("template_rmse", f"WITH {MEDIAN}, q AS (SELECT p, avg(val) AS m FROM px GROUP BY p) SELECT round(sqrt(avg((val - m) * (val - m))), 5) + 0.0 AS rmse FROM med JOIN q USING (p)")
def template_rmse(spark, sf):
    """Against the mean frame, the closed form for rows without a cycle."""
    t = tile_template(spark, sf).withColumn("video_id", F.lit("0"))
    mean = frames.pixels(emb_frames(spark, sf)).groupBy((F.col("y") * 8 + F.col("x")).alias("p")).agg(F.avg("val").alias("val"))
    truth = mean.withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(M - 1)))).withColumn("video_id", F.lit("0"))
    return metrics.template_rmse(t, truth).select(F.round("rmse", 5).alias("rmse"))


@query("residual_energy", f"WITH {MEDIAN}, q AS (SELECT p, median(val) AS m FROM px GROUP BY p) SELECT round(avg((val - m) * (val - m)), 5) + 0.0 AS e FROM med JOIN q USING (p)")
def residual_energy(spark, sf):
    t = tile_template(spark, sf).withColumn("video_id", F.lit("0"))
    mid = frames.pixels(emb_frames(spark, sf)).groupBy((F.col("y") * 8 + F.col("x")).alias("p")).agg(F.median("val").alias("val"))
    clean = mid.withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(M - 1)))).withColumn("video_id", F.lit("0"))
    return metrics.residual_energy(t, clean).select(F.round("e", 5).alias("e"))


@query("xt_slice", f"WITH {PX} SELECT t, p % 8 AS x, {r('val')} AS val FROM px WHERE p // 8 = 3")
def xt_slice(spark, sf):
    return metrics.xt_slice(frames.pixels(emb_frames(spark, sf)), 3).select("t", "x", "val")


@query(
    "cycle_deviation",
    f"""WITH {PLANTED}, mid AS (SELECT t % 12 AS j, median(v) AS mid FROM s GROUP BY 1)
SELECT t // 12 AS cycle, {r('sqrt(avg((v - mid) * (v - mid)))')} AS rms, count(*) AS n FROM s JOIN mid ON mid.j = s.t % 12 GROUP BY 1""",
)
def cycle_deviation(spark, sf):
    s = planted_series(spark, sf)
    middle = s.groupBy(F.pmod("t", F.lit(12)).alias("j")).agg(F.median("v").alias("v"))
    angle = F.lit(TAU) * (F.col("t") + 1e-9) / 12
    phi = s.select(F.col("t").alias("i"), F.pmod(angle, F.lit(TAU)).alias("phi"), angle.alias("phi_u"))
    return metrics.cycle_deviation(s.select("t", "v"), phi, middle, 12)


# --- homology ---------------------------------------------------------------------------------


def points(spark, video, coords):
    rows = [(video, i, [float(c) for c in p]) for i, p in enumerate(coords)]
    f = spark.createDataFrame(rows, "video_id string, t int, px array<double>")
    return f.select("video_id", "t", F.lit(1).alias("h"), F.lit(1).alias("w"), F.lit(1).alias("ch"), "px")


def polygon(n):
    return [(math.cos(TAU * i / n), math.sin(TAU * i / n)) for i in range(n)]


@query("rips_polygon", f"SELECT n, {r('2 * sin(pi() / n)')} AS birth, {r('2 * sin(pi() * ceil(n / 3.0) / n)')} AS death FROM (SELECT unnest([4, 6, 12, 20, 33]) AS n)")
def rips_polygon(spark, sf):
    all_points = None
    for n in (4, 6, 12, 20, 33):
        one = points(spark, str(n), polygon(n))
        all_points = one if all_points is None else all_points.unionByName(one)
    return homology.rips_h1(gram.distance_matrices(all_points)).select(F.col("video_id").cast("int").alias("n"), "birth", "death")


def two_harmonics(n=60, ratio=2.0):
    return [(math.cos(a), math.sin(a), ratio * math.cos(2 * a), ratio * math.sin(2 * a)) for a in (TAU * i / n for i in range(n))]


#: By ratio of the second harmonic to the first and field, the chords at which loops of 60 points begin and end.
FIELD_BARS = [
    (0.3, "any", 1, 1, 20), (0.6, "any", 1, 1, 30), (1.0, "two", 1, 1, 29), (1.0, "two", 2, 10, 12), (1.0, "odd", 1, 1, 12), (1.5, "two", 1, 1, 29), (1.5, "two", 2, 30, 11),
    (1.5, "odd", 1, 1, 11), (2.0, "two", 1, 30, 11), (2.0, "two", 2, 1, 29), (2.0, "odd", 1, 1, 11), (3.0, "two", 1, 30, 20), (3.0, "two", 2, 1, 29), (3.0, "odd", 1, 1, 20),
]


def chord(step: str) -> str:
    return f"sqrt(2 * (1 - cos({TAU} * {step} / 60)) + ratio * ratio * 2 * (1 - cos({TAU} * 2 * {step} / 60)))"


@query(
    "rips_field",
    f"""WITH b AS (SELECT * FROM (VALUES {", ".join(f"({a}::DOUBLE, '{k}', {rank}, {i}, {j})" for a, k, rank, i, j in FIELD_BARS)}) v(ratio, field, rank, i, j))
SELECT ratio, p, rank::BIGINT AS rank, {r(chord('i'))} AS birth, {r(chord('j'))} AS death FROM b, (SELECT unnest([2, 3, 7, 49]) AS p) WHERE field = 'any' OR (field = 'two') = (p = 2)""",
)
def rips_field(spark, sf):
    """The lasting bars of a loop whose second harmonic grows: from as strong as the first on, the loop splits
    over two elements, and over no odd field. Beginnings and ends are chords of the curve."""
    ratios = (0.3, 0.6, 1.0, 1.5, 2.0, 3.0)
    m = storage.materialise(gram.distance_matrices(workloads.union([points(spark, str(a), two_harmonics(60, a)) for a in ratios])))
    found = workloads.union([homology.rips_h1(m, p).withColumn("p", F.lit(p)) for p in (2, 3, 7, 49)])
    return found.filter("persistence > 0.2").select(F.col("video_id").cast("double").alias("ratio"), "p", "rank", "birth", "death")


def spanning_tree(n_rounds: int = 9) -> str:
    """CTEs with the edge lengths of a minimal spanning tree: every component takes its shortest edge out, until one is left."""
    parts = [f"{PAIRS}, e AS MATERIALIZED (SELECT i, j, d2 FROM pairs UNION ALL SELECT j, i, d2 FROM pairs), c0 AS (SELECT vec_id AS i, vec_id AS c FROM embeddings)"]
    for k in range(n_rounds):
        parts.append(
            f"m{k} AS MATERIALIZED (SELECT a.c, arg_min(b.c, d2) AS t, min(d2) AS d2 FROM e JOIN c{k} a ON e.i = a.i JOIN c{k} b ON e.j = b.i WHERE a.c <> b.c GROUP BY a.c),"
            f" p{k}_0 AS MATERIALIZED (SELECT x.c, CASE WHEN y.t = x.c AND x.c < x.t THEN x.c ELSE x.t END AS t FROM m{k} x JOIN m{k} y ON y.c = x.t)"
        )
        parts += [f"p{k}_{s + 1} AS MATERIALIZED (SELECT x.c, y.t FROM p{k}_{s} x JOIN p{k}_{s} y ON y.c = x.t)" for s in range(9)]
        parts.append(f"c{k + 1} AS MATERIALIZED (SELECT i, coalesce(t, c{k}.c) AS c FROM c{k} LEFT JOIN p{k}_9 ON p{k}_9.c = c{k}.c)")
    return ", ".join(parts) + f", tree AS (SELECT DISTINCT d2 FROM ({' UNION ALL '.join(f'SELECT d2 FROM m{k}' for k in range(n_rounds))}))"


@query("rips_edges_h0", f"WITH {spanning_tree()} SELECT row_number() OVER (ORDER BY d2) AS rank, {r('sqrt(d2)')} AS len FROM tree")
def rips_edges_h0(spark, sf):
    return homology.h0_deaths_of_frames(emb_frames(spark, sf)).select("rank", "len")


def farthest(m: int) -> str:
    """CTEs s0 to s(m-1): each the point farthest from those before it."""
    parts = [f"{PAIRS}, f AS MATERIALIZED (SELECT i, j, d2 FROM pairs UNION ALL SELECT j, i, d2 FROM pairs UNION ALL SELECT vec_id, vec_id, 0 FROM embeddings)", "s0 AS (SELECT 0::BIGINT AS i)", "n0 AS MATERIALIZED (SELECT j AS i, d2 AS v FROM f WHERE i = 0)"]
    for k in range(1, m):
        parts.append(f"s{k} AS MATERIALIZED (SELECT i FROM n{k - 1} ORDER BY v DESC, i LIMIT 1)")
        parts.append(f"n{k} AS MATERIALIZED (SELECT a.i, least(v, d2) AS v FROM n{k - 1} a JOIN f ON f.j = a.i AND f.i = (SELECT i FROM s{k}))")
    return ", ".join(parts)


@query("landmarks_maxmin", f"WITH {farthest(20)} {' UNION ALL '.join(f'SELECT {k}::BIGINT AS rank, i AS vec_id FROM s{k}' for k in range(20))}")
def landmarks_maxmin(spark, sf):
    return homology.landmark_frames(emb_frames(spark, sf), 20).select("rank", F.col("i").alias("vec_id"))


@query("rips_embeddings", "SELECT '0' AS video_id, true AS weak FROM range(1)")
def rips_embeddings(spark, sf):
    """Bars of the table's own order, by landmarks; a control without a cycle: no loop stands out."""
    marks = homology.landmark_frames(emb_frames(spark, sf), 60)
    strength = homology.loop_strength(homology.rips_h1(gram.distance_matrices(marks.withColumnRenamed("rank", "t"))))
    return strength.select("video_id", (F.coalesce("ratio", F.lit(1.0)) < 1.5).alias("weak"))


@query(
    "auto_scale",
    f"""WITH bars AS (SELECT l_returnflag AS video_id, l_discount AS birth, l_discount + l_extendedprice AS death FROM lineitem),
s AS (SELECT *, row_number() OVER (PARTITION BY video_id ORDER BY death - birth DESC, birth) AS k FROM bars)
SELECT video_id, alpha, {r('alpha * birth + (1 - alpha) * death')} AS sigma FROM s, (SELECT unnest([0.0, 0.25, 0.5, 0.75, 1.0])::DOUBLE AS alpha) WHERE k = 1""",
)
def auto_scale(spark, sf):
    """Every line is a bar, born at its discount and lasting its price; a scale for each return flag."""
    birth = F.col("l_discount")
    bars = table(spark, sf, "lineitem").select(F.col("l_returnflag").alias("video_id"), birth.alias("birth"), (birth + F.col("l_extendedprice")).alias("death"))
    return homology.auto_scale(bars, spark.createDataFrame([(a / 4,) for a in range(5)], "alpha double"), ["video_id"])


# --- baselines and corruptions ----------------------------------------------------------------


@query("bandpass_power", f"WITH {PLANTED} SELECT bin, {r(f'(pow(sum(v * cos({TAU} * bin * t / {BUCKETS})), 2) + pow(sum(v * sin({TAU} * bin * t / {BUCKETS})), 2)) / ({BUCKETS} * {BUCKETS})')} AS power FROM s, (SELECT unnest(range(1, 65)) AS bin) GROUP BY bin")
def bandpass_power(spark, sf):
    return baselines.power(planted_series(spark, sf), BUCKETS, list(range(1, 65)))


@query("best_loop", f"WITH {PAIRS} SELECT i AS start, j - i AS len, {r('d2')} AS d2 FROM pairs WHERE j - i BETWEEN 5 AND 60 ORDER BY pairs.d2, i LIMIT 1")
def best_loop(spark, sf):
    return baselines.best_loop_of_frames(emb_frames(spark, sf), 5, 60).select("start", "len", "d2")


@query(
    "jump_table",
    f"""WITH {PAIRS}, f AS (SELECT i, j, d2 FROM pairs UNION ALL SELECT j, i, d2 FROM pairs), w AS (SELECT i - 1 AS i, j, exp(-sqrt(d2) / 0.25) AS w FROM f WHERE i > 0)
SELECT i, j, {r('w / sum(w) OVER (PARTITION BY i)')} AS p FROM w""",
)
def jump_table(spark, sf):
    return baselines.jump_table_of_frames(emb_frames(spark, sf), 0.25).select("i", "j", "p")


def shuffled(spark, sf, cycles: float):
    """60 frames of a planted recording without their order: t is hashed. Adds the true place as column at."""
    g = workloads.grid(spark, "none", [0.0], (1,), (cycles,))
    f = synth.planted(spark, table(spark, sf, "embeddings"), g, 60, 16, 16, 3)
    key = F.row_number().over(window.Window.partitionBy("video_id").orderBy(F.md5(F.col("t").cast("string"))))
    return storage.materialise(f.withColumn("at", F.col("t")).withColumn("t", key - 1))


@query("spectral_order_line", "SELECT 60 AS n, true AS in_order FROM range(1)")
def spectral_order_line(spark, sf):
    """Frames of a third of a cycle without order: the first mode that is not constant puts them in a line."""
    f = shuffled(spark, sf, 1 / 3)
    order = baselines.spectral_order(gram.distance_matrices(f), "line").join(f.select(F.col("t").alias("i"), "at"), "i")
    step = F.abs(F.col("at") - F.lag("at").over(window.Window.partitionBy(F.lit(0)).orderBy("pos")))
    return order.withColumn("step", step).agg(F.count("*").alias("n"), (F.max("step") == 1).alias("in_order"))


@query("spectral_order_loop", "SELECT 60 AS n, true AS in_order FROM range(1)")
def spectral_order_loop(spark, sf):
    """Frames of one whole cycle without order: the phase of the first two modes puts them around the loop."""
    f = shuffled(spark, sf, 1.0)
    order = baselines.spectral_order(gram.distance_matrices(f), "loop").join(f.select(F.col("t").alias("i"), "at"), "i")
    step = F.pmod(F.col("at") - F.lag("at").over(window.Window.partitionBy(F.lit(0)).orderBy("pos")), F.lit(60))
    return order.withColumn("step", F.least(step, 60 - step)).agg(F.count("*").alias("n"), (F.max("step") == 1).alias("in_order"))


def hex32(key: str) -> str:
    return f"('0x' || substr(md5({key}), 1, 8))::BIGINT / 4294967296.0"


@query(
    "noise_frames",
    f"""WITH {PX}, u AS (SELECT t, p, val, greatest({hex32("concat_ws('|', '42', t::VARCHAR, p::VARCHAR, 'u')")}, pow(2.0, -33)) AS u, {hex32("concat_ws('|', '42', t::VARCHAR, p::VARCHAR, 'v')")} AS v FROM px)
SELECT t, p, {r(f'val + 0.5 * (sqrt(-2 * ln(u)) * cos({TAU} * v))')} AS val FROM u""",
)
def noise_frames(spark, sf):
    px = frames.pixels(emb_frames(spark, sf)).withColumn("p", F.col("y") * SIDE + F.col("x"))
    return px.select("t", "p", (F.col("val") + 0.5 * normal(F.lit(42), F.col("t"), F.col("p"))).alias("val"))


WALK = (
    "steps AS (SELECT t, ({y} - 0.5) * 4 AS dy, ({x} - 0.5) * 4 AS dx, ({c} - 0.5) * 0.1 AS dc FROM (SELECT vec_id AS t FROM embeddings)),"
    " walk AS (SELECT t, sum(dy) OVER (ORDER BY t) + 3 AS y, sum(dx) OVER (ORDER BY t) + 3 AS x, sum(dc) OVER (ORDER BY t) + 0.5 AS c FROM steps)"
).format(**{k: hex32(f"concat_ws('|', '42', t::VARCHAR, '{k}')") for k in "yxc"})


def folded(v: str, most: float) -> str:
    return f"abs((({v}) - {2 * most} * floor(({v}) / {2 * most} + 0.5)))"


@query("occluder_path", f"WITH {WALK} SELECT t, {r(folded('y', 6.0))} AS y, {r(folded('x', 6.0))} AS x, {r(folded('c', 1.0))} AS colour FROM walk")
def occluder_path(spark, sf):
    return corrupt.occluder_path(table(spark, sf, "embeddings").select(F.col("vec_id").alias("t")), 6.0)


@query(
    "shake_kernel",
    f"""WITH s AS (SELECT t, k, floor({hex32("concat_ws('|', '42', t::VARCHAR, k::VARCHAR, 'y')")} * 3)::BIGINT - 1 AS dy, floor({hex32("concat_ws('|', '42', t::VARCHAR, k::VARCHAR, 'x')")} * 3)::BIGINT - 1 AS dx
  FROM (SELECT vec_id AS t FROM embeddings), (SELECT unnest(range(10)) AS k)),
w AS (SELECT t, least(greatest(sum(dy) OVER v, -2), 2)::BIGINT AS y, least(greatest(sum(dx) OVER v, -2), 2)::BIGINT AS x FROM s WINDOW v AS (PARTITION BY t ORDER BY k))
SELECT t, y, x, {r('count(*) / 10.0')} AS weight FROM w GROUP BY ALL""",
)
def shake_kernel(spark, sf):
    return corrupt.shake_kernel(table(spark, sf, "embeddings").select(F.col("vec_id").alias("t")), 5)


def shortest(steps: int = 16) -> str:
    """CTEs up to the shortest paths of at most ``steps`` + 1 edges on the neighbour graph."""
    parts = [
        f"""{PAIRS}, f AS (SELECT i, j, d2 FROM pairs UNION ALL SELECT j, i, d2 FROM pairs), k AS (SELECT i, j, d2, row_number() OVER (PARTITION BY i ORDER BY d2, j) AS rnk FROM f),
g AS MATERIALIZED (SELECT DISTINCT i, j, w FROM (SELECT i, j, sqrt(d2) AS w FROM k WHERE rnk <= 8 UNION ALL SELECT j, i, sqrt(d2) FROM k WHERE rnk <= 8)), p0 AS (SELECT i, j, w AS dist FROM g)"""
    ]
    parts += [f"p{s + 1} AS MATERIALIZED (SELECT i, j, min(dist) AS dist FROM (SELECT i, j, dist FROM p{s} UNION ALL SELECT p.i, g.j, p.dist + g.w FROM p{s} p JOIN g ON g.i = p.j) GROUP BY i, j)" for s in range(steps)]
    return ", ".join(parts)


@query("geodesic_hops", f"WITH {shortest()} SELECT i, j, {r('dist')} AS dist FROM p16 WHERE i < j")
def geodesic_hops(spark, sf):
    """Shortest paths along the neighbour graph."""
    return period.geodesics_of_frames(emb_frames(spark, sf)).select("i", "j", "dist")


# --- the rest of the data model -----------------------------------------------------------------


@query("frame_quantised", f"WITH {PX} SELECT t, p, round(greatest(least(val, 1.0), 0.0) * 255) + 0.0 AS val FROM px")
def frame_quantised(spark, sf):
    """Frames clipped and rounded to 256 levels, as a sink of images stores them."""
    return frames.quantised(emb_frames(spark, sf)).select("t", F.posexplode("px").alias("p", "val"))


@query("frame_grayscale", f"WITH {PX} SELECT t, p, 1::BIGINT AS ch, round(val * 0.299 + 2 * val * 0.587 + 3 * val * 0.114, 5) + 0.0 AS val FROM px", digits=5)
def frame_grayscale(spark, sf):
    """Three channels, here multiples of one, mixed to one."""
    colour = emb_frames(spark, sf).withColumn("px", F.flatten(F.transform(F.col("px").cast("array<double>"), lambda v: F.array(v, 2 * v, 3 * v)))).withColumn("ch", F.lit(3))
    return frames.grayscale(colour).select("t", "ch", F.posexplode("px").alias("p", "val"))


@query("ideal_circle", f"WITH {RECORDINGS} SELECT video_id, m, {r(f'2 - 2 * cos({TAU} * m / {N})')} AS {LAMBDA}, 0.0::DOUBLE AS resid FROM rec, (SELECT unnest(range(1, {N // 2 + 1})) AS m)")
def ideal_circle(spark, sf):
    """One period only: the circle graph of each recording's windows, its spectrum and its modes."""
    entries = customer_entries(spark, sf, 1, N)
    return spectral.circulant_spectrum(entries, N).join(spectral.ideal_residual(entries, 1, N), ["video_id", "m"]).select("video_id", "m", "lambda", "resid")


@query("spectrum_gap", "SELECT '0' AS video_id, 0.0::DOUBLE AS gap FROM range(1)")
def spectrum_gap(spark, sf):
    """Computed low modes of the ideal graph against the closed form."""
    found = spectral.low_modes(spectral.ideal_laplacian(spark, K, T).select(F.lit("0").alias("video_id"), "i", "j", "val"))
    twice = spectral.ideal_spectrum(spark, K, T).select(F.explode(F.when(F.col("m") < K * T // 2, F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(0)))), "lambda")
    rank = F.row_number().over(window.Window.partitionBy(F.lit(0)).orderBy("lambda"))
    return metrics.spectrum_gap(found.select("video_id", "rank", "lambda"), twice.select("lambda", rank.alias("rank")))


@query("stage_cost", "SELECT 'Exchange' AS operator, 1 AS n FROM range(1)")
def stage_cost(spark, sf):
    """The exchanges of phase inference from stored frames: one."""
    from ..config import FoldConfig
    from ..plans import pipeline

    return metrics.stage_cost(pipeline.inferred(emb_frames(spark, sf), FoldConfig(pyramid_level=1))).filter("operator = 'Exchange'")
