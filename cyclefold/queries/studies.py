"""The experiments as queries: full folds, sweeps under corruption, controls.

Each query returns the conditions that it ran and what was found in them, so that SQL can state what
must be found; ``experiments.py`` prints the errors themselves with their spread.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import FoldConfig
from ..functions.angles import TAU
from ..operators import baselines, frames, gram, homology, metrics, window
from ..plans import pipeline, regimes, storage, synth, workloads
from .methods import BUCKETS, M, buckets, planted_series
from .registry import query, table

FRAMES, SIDE, CHANNELS = 600, 32, 3
MAX_N = 120
CONFIG = FoldConfig(max_n=MAX_N)
SERIES_CONFIG = FoldConfig(M=48, tmin=6)
#: Mean errors in degrees under which a phase counts as good, and over which it counts as lost.
GOOD, LOST = 6.0, 45.0

SCENES = "(SELECT unnest([1, 2, 3]) AS scene)"


def listed(values) -> str:
    return ", ".join(f"{v!r}::DOUBLE" for v in map(float, values))


# --- one series ---------------------------------------------------------------------------------


def w_1d(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    """The two-hour series with a planted season, and its true phase."""
    s = planted_series(spark, sf).withColumn("series_id", F.lit("events"))
    return s.select("series_id", "t", "v"), s.select(F.col("series_id").alias("video_id"), "t", "phi")


@query("fold_1d", f"SELECT 12::BIGINT AS period, 13::BIGINT AS d, {BUCKETS // 12}::BIGINT AS k, false AS fallback, true AS good")
def fold_1d(spark, sf):
    """The whole method on one series, nothing given: whole period and cycles, and whether the phase is right."""
    series, truth = w_1d(spark, sf)
    found = storage.materialise(pipeline.inferred_series(series, SERIES_CONFIG))
    error = metrics.angular_error(pipeline.phases(found).select("video_id", "i", "phi"), truth)
    whole = lambda c: F.round(c).cast("long").alias(c)
    return pipeline.runs(found).join(error, "video_id").select(whole("period"), "d", whole("k"), "fallback", (F.col("err_deg") < 2 * GOOD).alias("good"))


@query("fold_1d_errors", f"SELECT true AS k_close, true AS period_close FROM range(1)")
def fold_1d_errors(spark, sf):
    """Errors of the cycle count and of the period (share) stay small."""
    found = pipeline.runs(pipeline.inferred_series(w_1d(spark, sf)[0], SERIES_CONFIG))
    return metrics.cycle_error(found, BUCKETS / 12, 12.0).select((F.col("k_err") < 0.5).alias("k_close"), (F.col("period_err") < 0.02).alias("period_close"))


@query("fold_1d_template", "SELECT 48 AS angles, true AS all_voted, true AS close FROM range(1)")
def fold_1d_template(spark, sf):
    """The folded cycle against the planted season, after the best turn and in the better direction."""
    cycle = pipeline.fold_series(w_1d(spark, sf)[0], SERIES_CONFIG).select("j", "v", "n_votes")
    turn = F.explode(F.sequence(F.lit(0), F.lit(47))).alias("turn")
    each = cycle.select("j", "v", turn, F.explode(F.array(F.lit(1), F.lit(-1))).alias("dir"))
    angle = F.lit(TAU) * (F.col("dir") * F.col("j") + F.col("turn")) / 48
    off = each.withColumn("e", F.pow(F.col("v") - 4 * F.sin(angle) - 1.5 * F.sin(2 * angle), 2)).groupBy("turn", "dir").agg(F.sqrt(F.avg("e")).alias("rmse"))
    votes = cycle.agg(F.count("*").alias("angles"), F.min(F.col("n_votes") > 0).alias("all_voted"))
    return votes.join(off.agg((F.min("rmse") < 0.6).alias("close")))


@query("study_deviation", "SELECT (count(*) % 20 + 5)::BIGINT AS cycle, 12::BIGINT AS period, true AS stands_out FROM events")
def study_deviation(spark, sf):
    """One cycle, chosen by the table's size, is spoiled; the method finds the period, folds, and names the cycle."""
    spoiled = table(spark, sf, "events").agg((F.count("*") % 20 + 5).alias("spoiled"))
    s = planted_series(spark, sf).join(F.broadcast(spoiled))
    s = s.withColumn("v", F.when(F.floor(F.col("t") / 12) == F.col("spoiled"), -F.col("v")).otherwise(F.col("v")))
    series = storage.materialise(s.select(F.lit("events").alias("series_id"), F.col("t").cast("int").alias("t"), "v"))
    config = SERIES_CONFIG.but(d=13, M=12)
    found = storage.materialise(pipeline.inferred_series(series, config))
    period = pipeline.runs(pipeline.inferred_series(series, SERIES_CONFIG)).select(F.round("period").cast("long").alias("period"))
    template = pipeline.fold_series(series, config).select("j", "v")
    phi = pipeline.phases(found).select("i", "phi", (TAU * F.floor(F.col("i") / 12) + 1e-6).alias("phi_u"))  # cycles are counted from the first frame
    rms = metrics.cycle_deviation(series.select("t", "v"), phi, template, 12)
    best = rms.agg(F.max_by("cycle", "rms").alias("cycle"), F.max("rms").alias("top"), F.median("rms").alias("mid"))
    return best.join(period).select(F.col("cycle").cast("long"), "period", (F.col("top") > 2 * F.col("mid")).alias("stands_out"))


# --- one video ----------------------------------------------------------------------------------


def planted(spark, sf, scene=1, cycles=15, corruption="none", level=0.0, n=FRAMES):
    g = workloads.grid(spark, corruption, [level], (scene,), (cycles,))
    return synth.planted(spark, table(spark, sf, "embeddings"), g, n, SIDE, SIDE, CHANNELS), synth.truth(g, n)


@query("fold_video", "SELECT 40::BIGINT AS period, 41::BIGINT AS d, 15::BIGINT AS k, false AS fallback, true AS good FROM range(1)")
def fold_video(spark, sf):
    f, truth = planted(spark, sf, 2, corruption="noise", level=0.1)
    found = storage.materialise(pipeline.inferred(f, CONFIG))
    error = metrics.angular_error(pipeline.phases(found).select("video_id", "i", "phi"), truth)
    whole = lambda c: F.round(c).cast("long").alias(c)
    return pipeline.runs(found).join(error, "video_id").select(whole("period"), "d", whole("k"), "fallback", (F.col("err_deg") < GOOD).alias("good"))


@query("fold_video_template", f"SELECT j, tile, least(512, {SIDE * SIDE * CHANNELS} - 512 * tile)::BIGINT AS pixels, true AS voted FROM (SELECT unnest(range({M})) AS j), (SELECT unnest(range({SIDE * SIDE * CHANNELS // 512})) AS tile)")
def fold_video_template(spark, sf):
    f, _ = planted(spark, sf, 1, corruption="noise", level=0.1)
    out = pipeline.fold(storage.materialise(f), CONFIG.but(M=M, F=3.0, tile_px=512))
    return out.select("j", "tile", F.size("px").cast("long").alias("pixels"), (F.col("n_votes") > 0).alias("voted"))


@query("fold_segments", f"SELECT j, true AS voted, true AS close FROM (SELECT unnest(range(40)) AS j)")
def fold_segments(spark, sf):
    """An endless recording: longer than a task may hold, so it is folded in overlapping segments and merged.
    The template is compared with the clean cycle."""
    f, _ = planted(spark, sf, 1, 15, "noise", 0.05)
    out = pipeline.fold(storage.materialise(f), CONFIG.but(M=40, local_frames=250, overlap=50, tile_px=SIDE * SIDE * CHANNELS))
    import numpy as np

    clean = synth.frames_of(synth.basis_rows(table(spark, sf, "embeddings")), 1, 1, 40, SIDE, SIDE, ch=CHANNELS)

    def compare(pdf):
        pdf = pdf.sort_values("j")
        px = np.stack(pdf["px"].to_numpy()).astype(float)
        errors = [np.sqrt(((np.roll(t, s, axis=0) - clean) ** 2).mean(axis=1)) for t in (px, px[::-1]) for s in range(len(px))]
        return pdf.assign(voted=pdf["n_votes"] > 0, close=min(errors, key=lambda e: e.mean()) < 0.1)[["j", "voted", "close"]]

    return out.groupBy("video_id").applyInPandas(compare, "j int, voted boolean, close boolean")


@query("regime_plan", "SELECT '0' AS video_id, count(*) AS n, 64::BIGINT AS pixels, CASE WHEN count(*) > 2000 THEN 'endless' ELSE 'many' END AS regime FROM embeddings")
def regime_plan(spark, sf):
    return regimes.planned(frames.from_table(table(spark, sf, "embeddings"), None, "vec_id", "embedding", (8, 8, 1)))


# --- sweeps -------------------------------------------------------------------------------------


def sweep(spark, sf, workload, trials=1, scenes=(1, 2, 3), jitter=0.0, drift=0.0, **config):
    g, variants = workloads.study(spark, workload, SIDE, trials, scenes, **({"max_n": MAX_N} | config))
    return workloads.errors(spark, table(spark, sf, "embeddings"), g, variants, FRAMES, SIDE, SIDE, CHANNELS, jitter, drift)


def beside(found: DataFrame, *by: str) -> DataFrame:
    """(by), windowed, single: mean errors with and without windows, trials as n."""
    mean = lambda v: F.avg(F.when(F.col("variant") == v, F.col("err_deg"))).alias(v)
    return found.groupBy(*by).agg(mean("windowed"), mean("single"), F.count_if(F.col("variant") == "windowed").alias("n"), F.avg(F.when(F.col("variant") == "windowed", F.col("k"))).alias("k"))


def good():
    return (F.col("windowed") < GOOD).alias("good")


def better():
    return (F.col("windowed") < F.col("single")).alias("better")


@query("study_cycles", f"SELECT scene, cycles, true AS good, true AS better, true AS counted FROM {SCENES}, (SELECT unnest([{listed(workloads.CYCLES)}]) AS cycles)")
def study_cycles(spark, sf):
    """3 to 50 cycles in as many frames: windows give the phase and the number of cycles."""
    return beside(sweep(spark, sf, "cycles"), "scene", "cycles").select("scene", "cycles", good(), better(), (F.abs(F.col("k") - F.col("cycles")) < 0.1 + 0.01 * F.col("cycles")).alias("counted"))


@query("study_shake", f"SELECT scene, level, true AS good, true AS better FROM {SCENES}, (SELECT unnest([{listed(workloads.SHAKES)}]) AS level)")
def study_shake(spark, sf):
    """Blur kernels of 10 to 50 pixels of a frame 300 wide."""
    level = F.round(F.col("level") * 300 / SIDE, 3).alias("level")
    return beside(sweep(spark, sf, "shake"), "scene", "level").select("scene", level, good(), better())


@query(
    "study_noise",
    f"SELECT scene, level, scene <> 2 OR level < 1 AS good, true AS better FROM {SCENES}, (SELECT unnest([{listed(workloads.NOISES)}]) AS level) WHERE scene <> 2 OR level < 2",
)
def study_noise(spark, sf):
    """Severe noise is borne with windows. Where the second harmonic is the stronger one, noise of 1 costs accuracy
    and noise of 2, which is left out, hides the cycle from both (``experiments.py``)."""
    found = beside(sweep(spark, sf, "noise", 3), "scene", "level").filter("scene <> 2 or level < 2")
    return found.select("scene", "level", good(), better())


@query("study_surrogate", f"SELECT scene, level, true AS good FROM {SCENES}, (SELECT unnest([{listed(workloads.NOISES[:2])}]) AS level)")
def study_surrogate(spark, sf):
    """With the period from the autocorrelation of all coordinates, the strong second harmonic is no obstacle."""
    found = beside(sweep(spark, sf, "noise", 3, surrogate="distances").filter("level < 2"), "scene", "level")
    return found.select("scene", "level", good())


@query("study_occlusion", f"SELECT scene, level, CASE WHEN level <= 0.1 THEN true END AS good, CASE WHEN level <= 0.1 THEN true END AS better, level = 0.3 AS worse FROM {SCENES}, (SELECT unnest([{listed(workloads.SIDES)}]) AS level)")
def study_occlusion(spark, sf):
    """Moderate squares, up to a tenth of the height, are borne with windows; the largest are not. In between one
    trial of a few loses the cycle."""
    found = beside(sweep(spark, sf, "occlude", 3), "scene", "level")
    moderate = lambda c: F.when(F.col("level") <= 0.1, c)
    return found.select("scene", "level", moderate(good()).alias("good"), moderate(better()).alias("better"), ((F.col("level") == 0.3) & (F.col("windowed") > 2 * GOOD)).alias("worse"))


@query("study_missing", f"SELECT scene, true AS good, true AS better FROM {SCENES}")
def study_missing(spark, sf):
    """A tenth of the frames lost and refilled in time."""
    return beside(sweep(spark, sf, "missing"), "scene").select("scene", good(), better())


@query("study_alpha", f"SELECT scene, corruption, true AS stable FROM {SCENES}, (SELECT unnest(['none', 'shake', 'noise', 'occlude']) AS corruption)")
def study_alpha(spark, sf):
    """With windows the error hardly moves over the weight of birth against death, in every scene and under every corruption."""
    found = sweep(spark, sf, "alpha").filter("variant like 'windowed/%'")
    return metrics.alpha_spread(found, ["scene", "corruption"]).select("scene", "corruption", (F.col("spread") < 3).alias("stable"))


@query("study_alpha_windows", f"SELECT scene, corruption, true AS steadier FROM {SCENES}, (SELECT unnest(['none', 'shake', 'noise', 'occlude']) AS corruption)")
def study_alpha_windows(spark, sf):
    """Windows make the choice of the weight matter less."""
    found = sweep(spark, sf, "alpha").withColumn("window", F.substring_index("variant", "/", 1))
    spread = metrics.alpha_spread(found, ["scene", "corruption", "window"]).groupBy("scene", "corruption").pivot("window", ["windowed", "single"]).agg(F.first("spread"))
    return spread.select("scene", "corruption", (F.col("windowed") < F.col("single")).alias("steadier"))


@query(
    "study_kernel",
    f"""SELECT scene, level, kernel, pick, CASE WHEN kernel <> 'step' THEN scene <> 2 OR pick = 'zero_cross' END AS good
FROM {SCENES}, (SELECT unnest([0.0, 0.1, 0.5]::DOUBLE[]) AS level), (SELECT unnest(['gauss', 'printed', 'step']) AS kernel), (SELECT unnest(['zero_cross', 'first']) AS pick)""",
)
def study_kernel(spark, sf):
    """Weighted graphs and the choice of modes by zero crossings: the first two modes fail where the second
    harmonic is the stronger one. Unweighted graphs depend on the scale and are only reported by the script."""
    part = lambda k: F.substring_index("variant", "/", k)
    found = sweep(spark, sf, "kernel").groupBy("scene", "level", part(1).alias("kernel"), part(-1).alias("pick")).agg(F.avg("err_deg").alias("e"))
    return found.select("scene", "level", "kernel", "pick", F.when(F.col("kernel") != "step", F.col("e") < GOOD).alias("good"))


@query("study_trials", f"SELECT scene, 50 AS n, true AS good, true AS better, true AS steady FROM {SCENES} WHERE scene <> 2")
def study_trials(spark, sf):
    """50 trials of noise 1 as one job: mean and spread. Scene 2, which needs the other surrogate, is in ``study_surrogate``."""
    g = workloads.grid(spark, "noise", [1.0], (1, 3), trials=50)
    found = workloads.errors(spark, table(spark, sf, "embeddings"), g, workloads.windowed_or_not(max_n=MAX_N), FRAMES, SIDE, SIDE, CHANNELS)
    spread = found.filter("variant = 'windowed'").groupBy("scene").agg((F.stddev_samp("err_deg") < GOOD).alias("steady"))
    return beside(found, "scene").join(spread, "scene").select("scene", "n", good(), better(), "steady")


@query("study_given", f"SELECT scene, level, true AS same_period, true AS good FROM {SCENES}, (SELECT unnest([0.05, 0.1]::DOUBLE[]) AS level)")
def study_given(spark, sf):
    """What the recording decides by itself against what a user would give."""
    g = workloads.grid(spark, "occlude", [0.05, 0.1], (1, 2, 3))
    configs = {"auto": CONFIG, "given": CONFIG.but(period=FRAMES / 15, d=FRAMES // 15 + 1)}
    found = workloads.errors(spark, table(spark, sf, "embeddings"), g, configs, FRAMES, SIDE, SIDE, CHANNELS)
    pick = lambda v, c: F.max(F.when(F.col("variant") == v, F.col(c)))
    return found.groupBy("scene", "level").agg((F.abs(pick("auto", "period") - pick("given", "period")) < 0.5).alias("same_period"), (F.greatest(pick("auto", "err_deg"), pick("given", "err_deg")) < GOOD).alias("good"))


@query(
    "phases_corrupt_table",
    f"""WITH c AS (SELECT 'shake' AS corruption, round(unnest([{listed(workloads.SHAKES[:3])}]) * {SIDE} / 300, 3) AS level UNION ALL SELECT 'noise', unnest([{listed(workloads.NOISES[:2])}]) UNION ALL SELECT 'occlude', unnest([{listed(workloads.SIDES[:3])}])),
s AS (SELECT corruption, level FROM c, (SELECT unnest([1, 3]) AS scene))
SELECT corruption, level, grouping_id(corruption, level) AS g, count(*) AS n, true AS better FROM s GROUP BY ROLLUP (corruption, level)""",
)
def phases_corrupt_table(spark, sf):
    """By corruption and level, with subtotals: the mean error with windows is below that without."""
    parts = [sweep(spark, sf, w, scenes=(1, 3)) for w in ("shake", "noise", "occlude")]
    found = workloads.union(parts).filter("corruption = 'shake' and level < 4 or corruption = 'noise' and level < 2 or corruption = 'occlude' and level < 0.2")
    found = storage.materialise(found.withColumn("level", F.round("level", 3)))
    mean = lambda v: F.avg(F.when(F.col("variant") == v, F.col("err_deg")))
    rolled = found.rollup("corruption", "level").agg(F.grouping_id().alias("g"), F.count_if(F.col("variant") == "windowed").alias("n"), (mean("windowed") < mean("single")).alias("better"))
    return rolled


@query("study_landmarks", "SELECT scene, max_n, true AS close FROM (SELECT unnest([1, 3]) AS scene), (SELECT unnest([60, 90, 120]) AS max_n)")
def study_landmarks(spark, sf):
    """Barcodes on landmarks against exact ones: the scale moves by less than a tenth, the phase by less than a degree."""
    g = workloads.grid(spark, "noise", [0.5], (1, 3), (10,))
    configs = {f"{m}": FoldConfig(max_n=m) for m in (60, 90, 120)} | {"exact": FoldConfig(max_n=None)}
    found = storage.materialise(workloads.errors(spark, table(spark, sf, "embeddings"), g, configs, 240, SIDE, SIDE, CHANNELS))
    exact = found.filter("variant = 'exact'").select("video_id", F.col("sigma").alias("s"), F.col("err_deg").alias("e"))
    both = found.filter("variant <> 'exact'").join(exact, "video_id")
    return both.select("scene", F.col("variant").cast("int").alias("max_n"), ((F.abs(F.col("sigma") / F.col("s") - 1) < 0.1) & (F.abs(F.col("err_deg") - F.col("e")) < 1)).alias("close"))


@query("study_window", "SELECT d, true AS beats_neighbours, d = 41 AS best FROM (SELECT unnest([21, 41]) AS d)")
def study_window(spark, sf):
    """Persistence of the loop, per root of the window, as the window grows from a quarter to two and a half periods
    of 20: whole periods beat the windows around them, and one of them is the best of all. (Half periods beat theirs
    too where, as here, a second harmonic is strong.) Barcodes are exact."""
    series = spark.range(200).select(F.lit("x").alias("video_id"), F.col("id").cast("int").alias("t"), (F.sin(F.lit(TAU) * F.col("id") / 20) + 0.5 * F.sin(F.lit(2 * TAU) * F.col("id") / 20)).alias("v"))
    lengths = (5, 11, 16, 21, 26, 31, 36, 41, 46, 51)
    stacked = [window.stack(series, d, by=["video_id"]).select(F.lit(str(d)).alias("video_id"), F.col("i").alias("t"), F.lit(1).alias("h"), F.lit(1).alias("w"), F.lit(1).alias("ch"), F.col("w").alias("px")) for d in lengths]
    bars = homology.strongest(homology.rips_h1(gram.distance_matrices(workloads.union(stacked))), ["video_id"])
    d = F.col("video_id").cast("int")
    strength = bars.select(d.alias("d"), ((F.col("death") - F.col("birth")) / F.sqrt(d)).alias("strength"))
    order, whole = window.Window.partitionBy(F.lit(0)).orderBy("d"), window.Window.partitionBy(F.lit(0))
    around = F.greatest(F.lag("strength").over(order), F.lead("strength").over(order))
    seen = strength.select("d", (F.col("strength") > around).alias("beats_neighbours"), (F.col("strength") == F.max("strength").over(whole)).alias("best"))
    return seen.filter("d in (21, 41)")


@query("study_fan", "SELECT true AS good, true AS better, true AS period_close FROM range(1)")
def study_fan(spark, sf):
    """Six frames a period, slightly off, so that phases interleave."""
    g = workloads.grid(spark, "none", [0.0], (1,), (FRAMES / 6.13,))
    found = storage.materialise(workloads.errors(spark, table(spark, sf, "embeddings"), g, workloads.windowed_or_not(max_n=MAX_N), FRAMES, SIDE, SIDE, CHANNELS))
    period = found.filter("variant = 'windowed'").select((F.abs(F.col("period") - 6.13) < 0.1).alias("period_close"))
    return beside(found, "scene").select(good(), better()).join(period)


@query("study_fan_template", "SELECT j, true AS voted FROM (SELECT unnest(range(60)) AS j)")
def study_fan_template(spark, sf):
    """Ten times as many frames of one cycle as a period of the recording has."""
    f, _ = planted(spark, sf, 1, FRAMES / 6.13)
    out = pipeline.fold(storage.materialise(f), CONFIG.but(M=60, tile_px=SIDE * SIDE * CHANNELS))
    return out.select("j", (F.col("n_votes") > 0).alias("voted"))


@query("study_control", "SELECT unnest(['carousel', 'order', 'raw']) AS video_id, true AS no_cycle")
def study_control(spark, sf):
    """No cycle, and no period given: the vectors in the table's order and by label, and the raw event series.
    Loops are weak, or no period is found at all."""
    e = table(spark, sf, "embeddings")
    by_label = window.Window.partitionBy(F.lit(0)).orderBy("label", "vec_id")  # a control of a bounded number of rows
    carousel = e.withColumn("vec_id", F.row_number().over(by_label).cast("long") - 1)
    both = workloads.union([frames.from_table(x, None, "vec_id", "embedding", (8, 8, 1)).withColumn("video_id", F.lit(n)) for n, x in (("order", e), ("carousel", carousel))])
    some = pipeline.runs(pipeline.inferred(both.filter("t < 500"), FoldConfig(max_n=60, pyramid_level=1)))
    raw = buckets(spark, sf).select(F.lit("raw").alias("series_id"), "t", "v")
    found = some.unionByName(pipeline.runs(pipeline.inferred_series(raw, SERIES_CONFIG.but(max_n=60))))
    return found.select("video_id", ((F.coalesce(F.col("loop_ratio"), F.lit(1.0)) < 1.5) | F.isnan("loop_ratio") | F.col("fallback")).alias("no_cycle"))


@query("study_alias", f"SELECT cycles, alias FROM (VALUES ({FRAMES * 0.8}::DOUBLE, {round(FRAMES * 0.2)}::BIGINT), ({FRAMES * 0.9}::DOUBLE, {round(FRAMES * 0.1)}::BIGINT), ({FRAMES * 0.95}::DOUBLE, {round(FRAMES * 0.05)}::BIGINT)) v(cycles, alias)")
def study_alias(spark, sf):
    """Fewer than two frames a period: the cycles that the frames show are those beyond whole turns, run backwards."""
    g = workloads.grid(spark, "none", [0.0], (1,), (FRAMES * 0.8, FRAMES * 0.9, FRAMES * 0.95))
    found = workloads.errors(spark, table(spark, sf, "embeddings"), g, {"windowed": CONFIG}, FRAMES, SIDE, SIDE, CHANNELS)
    return found.select("cycles", F.round("k").cast("long").alias("alias"))


@query("study_exercise", "SELECT corruption, level, true AS good, true AS better FROM (VALUES ('none', 0.0::DOUBLE), ('noise', 0.5), ('noise', 1.0)) v(corruption, level)")
def study_exercise(spark, sf):
    """The busy scene with amplitudes that vary from cycle to cycle and brightness that drifts, clean and under noise."""
    g = workloads.union([workloads.grid(spark, "none", [0.0], (3,)), workloads.grid(spark, "noise", [0.5, 1.0], (3,))])
    found = workloads.errors(spark, table(spark, sf, "embeddings"), g, workloads.windowed_or_not(max_n=MAX_N), FRAMES, SIDE, SIDE, CHANNELS, 0.2, 0.3)
    return beside(found, "corruption", "level").select("corruption", "level", good(), better())


@query("study_slices", "SELECT unnest(['0', '1']) AS video_id, true AS smoother_than_input, true AS smoother_than_sorted")
def study_slices(spark, sf):
    """A jittered recording as it is, reordered by phase, and as median template: mean squared steps between
    successive frames of one cycle."""
    import numpy as np
    import pandas as pd

    basis = synth.basis_rows(table(spark, sf, "embeddings"))

    def run(batches):
        for pdf in batches:
            for k in pdf["id"]:
                px = synth.frames_of(basis, 2, 15, FRAMES, SIDE, SIDE, 0.4, int(k), CHANNELS)
                yield pd.DataFrame({"video_id": str(k), "t": np.arange(FRAMES, dtype="int32"), "h": SIDE, "w": SIDE, "ch": CHANNELS, "px": list(px.astype(np.float32))})

    f = storage.materialise(spark.range(2).mapInPandas(run, "video_id string, t int, h int, w int, ch int, px array<float>"))
    config = CONFIG.but(M=60, F=3.0, tile_px=SIDE * SIDE * CHANNELS)
    found = storage.materialise(pipeline.inferred(f, config))
    given = f.select("video_id", F.lit("input").alias("kind"), F.col("t").alias("pos"), "px")
    order = baselines.sort_by_phase(pipeline.phases(found))
    simple = order.join(f.select("video_id", "t", "px"), ["video_id", "t"]).select("video_id", F.lit("simple").alias("kind"), "pos", "px")
    middle = pipeline.fold(f, config, found).select("video_id", F.lit("median").alias("kind"), F.col("j").alias("pos"), "px")
    e = metrics.seam_energy(given.unionByName(simple).unionByName(middle), ["video_id", "kind"]).groupBy("video_id").pivot("kind", ["input", "simple", "median"]).agg(F.first("e"))
    return e.select("video_id", (F.col("median") < F.col("input")).alias("smoother_than_input"), (F.col("median") < F.col("simple")).alias("smoother_than_sorted"))


@query("study_blood", "SELECT scene, kind, true AS good, true AS better_than_faint FROM (SELECT unnest([1, 3]) AS scene), (SELECT unnest(['amplified']) AS kind)")
def study_blood(spark, sf):
    """Changes too small to see, under noise, amplified in their band and folded with windows: the phase is
    better than without the amplification, which removes what lies outside the band."""
    g = workloads.grid(spark, "noise", [0.5], (1, 3), (24,))
    f = synth.planted(spark, table(spark, sf, "embeddings"), g, FRAMES, SIDE, SIDE, CHANNELS)
    faint = storage.materialise(f.withColumn("px", F.transform("px", lambda x: (x * 0.1).cast("float"))))
    tiles = frames.tiles(faint, SIDE * SIDE * CHANNELS)
    loud = baselines.bandpass(tiles, 20 / FRAMES, 28 / FRAMES, 10.0).select("video_id", "t", F.lit(SIDE).alias("h"), F.lit(SIDE).alias("w"), F.lit(CHANNELS).alias("ch"), "px")
    both = workloads.union([x.withColumn("video_id", F.concat_ws("/", F.lit(k), "video_id")) for k, x in (("faint", faint), ("amplified", loud))])
    phi = pipeline.phases(pipeline.inferred(both, CONFIG)).select("video_id", "i", "phi")
    truth = synth.truth(g, FRAMES)
    truth = workloads.union([truth.withColumn("video_id", F.concat_ws("/", F.lit(k), "video_id")) for k in ("faint", "amplified")])
    error = metrics.angular_error(phi, truth).select(F.substring_index("video_id", "/", 1).alias("kind"), F.substring_index("video_id", "/", -1).alias("video_id"), "err_deg")
    named = error.join(g.select("video_id", "scene"), "video_id").groupBy("scene").pivot("kind", ["faint", "amplified"]).agg(F.first("err_deg"))
    return named.select("scene", F.lit("amplified").alias("kind"), (F.col("amplified") < GOOD).alias("good"), (F.col("amplified") < F.col("faint")).alias("better_than_faint"))
