"""The pipeline on planted recordings, and the findings it must reproduce."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from cyclefold.config import FoldConfig
from cyclefold.operators import baselines, frames, gram, graph, homology, metrics, phase, pyramid, spectral, vote, window
from cyclefold.plans import corrupt, pipeline, regimes, storage, synth, workloads
from cyclefold.schema import BadInput

SMALL = dict(max_n=80, pyramid_level=1)


@pytest.fixture(scope="module")
def embeddings(spark):
    return spark.read.parquet("/root/testdata/sf0.001/embeddings.parquet")


def found(spark, embeddings, workload_grid, configs, n=200):
    rows = workloads.errors(spark, embeddings, workload_grid, configs, n, 8, 8).collect()
    return {(r.scene, r.cycles, r.level, r.trial, r.variant): r for r in rows}


def test_windows_beat_single_frames_under_noise(spark, embeddings):
    g = workloads.grid(spark, "noise", [0.1, 0.2], (1, 2), (10,), trials=2)
    rows = found(spark, embeddings, g, workloads.windowed_or_not(**SMALL))
    for scene in (1, 2):
        for level in (0.1, 0.2):
            w, s = (np.mean([rows[scene, 10.0, level, t, v].err_deg for t in (0, 1)]) for v in ("windowed", "single"))
            assert w < s
            assert w < 4 or (scene, level) == (2, 0.2)  # there the surrogate may take the second harmonic's period
    assert abs(rows[1, 10.0, 0.1, 0, "windowed"].k - 10) < 0.5


def test_alpha_hardly_matters_and_weights_beat_steps(spark, embeddings):
    g = workloads.grid(spark, "noise", [0.1], (2,), (10,))
    rows = found(spark, embeddings, g, workloads.alpha_variants(**SMALL) | workloads.kernel_variants(**SMALL))
    errors = [rows[2, 10.0, 0.1, 0, f"alpha={a}"].err_deg for a in workloads.ALPHAS[1:10]]
    assert max(errors) - min(errors) < 3
    assert rows[2, 10.0, 0.1, 0, "gauss/zero_cross"].err_deg < 5 < 45 < rows[2, 10.0, 0.1, 0, "gauss/first"].err_deg


def test_cycles_and_fan(spark, embeddings):
    rows = found(spark, embeddings, workloads.grid(spark, "none", [0.0], (1,), (3, 10, 25, 200 / 6.13)), {"w": FoldConfig(**SMALL)})
    for (_, cycles, *_), r in rows.items():
        assert r.err_deg < 5 and abs(r.period * cycles / 200 - 1) < 0.05


def test_fold_tiles_votes_and_the_median_beats_reordering(spark, embeddings):
    g = workloads.grid(spark, "noise", [0.1], (1,), (10,))
    f = storage.materialise(synth.planted(spark, embeddings, g, 200, 8, 8))
    frames.check(f)
    config = FoldConfig(**SMALL, M=40, F=3.0, tile_px=24)
    rows = storage.materialise(pipeline.inferred(f, config))
    phi = pipeline.phases(rows)
    error = metrics.angular_error(phi.select("video_id", "i", "phi"), synth.truth(g, 200)).first().err_deg
    assert error < 6
    t = pipeline.fold(f, config, rows)
    assert t.select("tile").distinct().count() == 3 and t.count() == 120
    whole = t.groupBy("j").agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("tile", "px"))), lambda r: r["px"])).alias("px"))
    simple = baselines.sort_by_phase(phi).join(f.select("t", "px"), "t").select(F.lit("simple").alias("kind"), "pos", "px")
    both = simple.unionByName(whole.select(F.lit("median").alias("kind"), F.col("j").alias("pos"), "px"))
    e = {r.kind: r.e for r in metrics.seam_energy(both, ["kind"]).collect()}
    assert 10 * e["median"] < e["simple"]
    assert {r.n_votes > 0 for r in t.collect()} == {True}


def test_huge_frames_sum_over_tiles_and_partitions_do_not_matter(spark, embeddings):
    f = frames.from_table(embeddings.filter("vec_id < 40"), None, "vec_id", "embedding", (8, 8, 1))
    a = {(r.i, r.j): r.d2 for r in gram.pair_distances(f, 64).collect()}
    b = {(r.i, r.j): r.d2 for r in gram.pair_distances(f.repartition(7), 10).collect()}
    c = {(r.i, r.j): r.d2 for r in gram.pair_distances_relational(f).collect()}
    assert a.keys() == b.keys() == c.keys() and all(abs(a[k] - b[k]) + abs(a[k] - c[k]) < 1e-9 for k in a)
    plan = gram.pair_distances(f, 64)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoop" not in plan


def exchanges(df):
    return df._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning")


def test_plans_move_pixels_once(spark, embeddings):
    stored = storage.materialise(frames.from_table(embeddings, None, "vec_id", "embedding", (8, 8, 1)))
    found = pipeline.inferred(stored, FoldConfig(**SMALL))
    assert exchanges(found) == 1
    template = pipeline.fold(stored, FoldConfig(**SMALL, tile_px=16), storage.materialise(found))
    plan = template._jdf.queryExecution().executedPlan().toString()
    assert plan.count("px#") and "CartesianProduct" not in plan and "BroadcastNestedLoop" not in plan
    scans = [line for line in plan.splitlines() if "ReadSchema" in line]
    assert sum("px:array" in line for line in scans) == 1  # the shapes that make the keys are read without pixels


def test_tiled_distances_give_the_same_phases(spark, embeddings):
    f = storage.materialise(synth.planted(spark, embeddings, workloads.grid(spark, "noise", [0.1], (1,), (10,)), 200, 8, 8))
    a, b = (pipeline.inferred(f, FoldConfig(**SMALL, gram_tile_px=t)).first() for t in (None, 20))
    assert np.allclose(a.phi, b.phi) and a.period == pytest.approx(b.period)


def test_edge_cases(spark):
    make = lambda px, v="a": [(v, t, 1, 2, 1, [float(x) for x in p]) for t, p in enumerate(px)]
    schema = "video_id string, t int, h int, w int, ch int, px array<float>"
    still = spark.createDataFrame(make([(1, 2)] * 30) + make([(np.sin(t), np.cos(t)) for t in range(50)], "b"), schema)
    rows = {r.video_id: r for r in pipeline.inferred(still, FoldConfig(pyramid_level=1)).collect()}
    assert rows["a"].fallback and not rows["b"].fallback and rows["b"].n == 50
    with pytest.raises(Exception, match="too few"):
        pipeline.inferred(spark.createDataFrame(make([(1, 2)] * 3), schema), FoldConfig(pyramid_level=1)).collect()
    with pytest.raises(BadInput):
        frames.check(spark.createDataFrame(make([(1, 2), (1, 2, 3)]), schema))
    with pytest.raises(BadInput):
        frames.check(still.filter("t <> 3"))
    with pytest.raises(ValueError):
        FoldConfig(alpha=2)
    assert FoldConfig().but(coeff=49).coeff == 49


def test_pyramid_layers(spark):
    image = np.arange(32 * 32, dtype=float).reshape(1, 32, 32, 1)
    assert pyramid.halve(pyramid.halve(image)).shape == (1, 8, 8, 1)
    assert np.allclose(pyramid.halve(np.ones((1, 7, 5, 3))), 1)
    f = spark.createDataFrame([("a", 0, 8, 8, 1, list(map(float, range(64))))], "video_id string, t int, h int, w int, ch int, px array<float>")
    kernel = pyramid.reduce(f, 2).first()
    assert (kernel.h, kernel.w) == (4, 4)
    long = {(r.y, r.x): r.val for r in pyramid.reduce_relational(frames.pixels(f), 8, 8).collect()}
    assert np.allclose(kernel.px, [long[y, x] for y in range(4) for x in range(4)], atol=1e-4)
    assert pyramid.reduce(f, 1) is f


def test_giant_graph_modes_by_power_steps(spark):
    lap = spectral.ideal_laplacian(spark, 3, 8)
    rows = spectral.block_power(lap, 24, q=4, steps=120).collect()
    values = {r.rank: r["lambda"] for r in rows}
    want = np.linalg.eigvalsh(spectral.ideal_matrix(3, 8))[1:3]
    assert np.allclose([values[1], values[2]], want, atol=1e-3)
    by = {r: sorted((x.i, x.v) for x in rows if x.rank == r) for r in (1, 2)}
    phi = np.arctan2([v for _, v in by[1]], [v for _, v in by[2]])
    from cyclefold.functions.kernels import angular_error

    assert angular_error(phi, 2 * np.pi * np.arange(24) / 8) < 2


def test_relational_phase_chain_equals_the_kernels(spark, embeddings):
    f = frames.from_table(embeddings.filter("vec_id < 60"), None, "vec_id", "embedding", (8, 8, 1))
    w = window.pair_distances(gram.pair_distances(f), 5)
    lap = graph.laplacian(graph.adjacency(w, 2.0))
    modes = storage.materialise(spectral.low_modes(lap))
    pair = phase.mode_pair(modes.select("video_id", "rank", "zero_cross"), by=["video_id"])
    got = {r.i: (r.phi, r.phi_u) for r in phase.unwrap(phase.from_modes(modes, pair)).collect()}
    from cyclefold.functions import kernels as k

    x = np.array([r.embedding for r in embeddings.filter("vec_id < 60").orderBy("vec_id").collect()], float)
    a = k.laplacian(k.adjacency(np.sqrt(k.window_distances(k.squared_distances(x), 5)), 2.0))
    _, vectors, _ = k.low_modes(a)
    p = k.mode_pair([k.zero_crossings(v) for v in vectors.T])[:2]
    phi, unwrapped = k.unwrap(k.phase(vectors, p))
    assert np.allclose(k.wrap(phi - np.array([got[i][0] for i in range(len(phi))])), 0, atol=1e-5)
    assert np.allclose(unwrapped, [got[i][1] for i in range(len(phi))], atol=1e-5)


def test_votes_relational_equals_kernel(spark):
    from cyclefold.functions import kernels as k

    phi = np.random.default_rng(0).uniform(0, 2 * np.pi, 30)
    table = spark.createDataFrame([("a", i, float(p)) for i, p in enumerate(phi)], "video_id string, i int, phi double")
    for near, anchor in ((None, "start"), (2.0, "start"), (2.0, "center")):
        got = {(r.j, r.i, r.a, r.b, round(r.frac, 6)) for r in vote.assign(table, 7, 5.0, 42, 13, near, anchor).collect()}
        j, i, a, b, frac, _ = k.votes(phi, 2 * np.pi * np.arange(7) / 7, 5.0, 42, 13, near, anchor)
        assert got == set(zip(j.tolist(), i.tolist(), a.tolist(), b.tolist(), np.round(frac, 6).tolist(), strict=True))


def test_corruptions_are_repeatable():
    px = np.random.default_rng(0).uniform(size=(40, 64))
    for kind, level in (("shake", 3), ("noise", 0.5), ("occlude", 0.3), ("drop", 0.2)):
        a, b, c = (corrupt.apply(px, 8, 8, kind, level, key) for key in ("k|0", "k|0", "k|1"))
        assert np.array_equal(a, b) and not np.array_equal(a, c) and a.shape == px.shape
    assert corrupt.apply(px, 8, 8, "none", 0, "k") is px


def test_segments_cover_and_merge(spark, embeddings):
    f = synth.planted(spark, embeddings, workloads.grid(spark, "none", [0.0], (1,), (12,)), 240, 8, 8)
    parts = storage.materialise(regimes.segments(f, 100, 30))
    sizes = {r.video_id.split("#")[1]: r.n for r in parts.groupBy("video_id").agg(F.count("*").alias("n")).collect()}
    assert sizes == {"0": 100, "1": 100, "2": 100, "3": 30}
    full = parts.filter("not video_id like '%#3'")
    out = regimes.merged(pipeline.fold(full, FoldConfig(**SMALL, M=20))).collect()
    assert len(out) == 20 and all(r.n_votes > 0 for r in out)
    px = np.array([r.px for r in sorted(out)], float)
    clean = synth.frames_of(synth.basis_rows(embeddings), 1, 1, 20, 8, 8)
    best = min(np.sqrt(((np.roll(t, s, axis=0) - clean) ** 2).mean()) for t in (px, px[::-1]) for s in range(20))
    assert best < 0.05


def test_baselines(spark, embeddings):
    series = spark.createDataFrame([(t, float(t % 5)) for t in range(50)], "t int, v double")
    assert [round(r["mean"], 6) for r in baselines.fold_known_period(series, 5, 5).orderBy("bin").collect()] == [0, 1, 2, 3, 4]
    f = frames.from_table(embeddings.filter("vec_id < 20"), None, "vec_id", "embedding", (8, 8, 1))
    jumps = baselines.jump_table(gram.pair_distances(f), 0.5).groupBy("i").agg(F.sum("p").alias("p")).collect()
    assert len(jumps) == 19 and all(abs(r.p - 1) < 1e-9 for r in jumps)
    line = spark.createDataFrame([("a", (7 * i) % 30, 1, 1, 1, [float(i)]) for i in range(30)], "video_id string, t int, h int, w int, ch int, px array<float>")
    order = [r.i for r in baselines.spectral_order(gram.distance_matrices(line), "line").orderBy("pos").collect()]
    where = [next(i for i in range(30) if (7 * i) % 30 == t) for t in order]
    assert where in (sorted(where), sorted(where)[::-1])
    tile = frames.tiles(spark.createDataFrame([("a", t, 1, 1, 1, [float(np.sin(2 * np.pi * t / 8))]) for t in range(64)], line.schema))
    loud = [r.px[0] for r in baselines.bandpass(tile, 0.1, 0.15, 2.0).orderBy("t").collect()]
    assert np.allclose(loud, 3 * np.sin(2 * np.pi * np.arange(64) / 8), atol=1e-5)


def test_homology_tables(spark):
    a = 2 * np.pi * np.arange(12) / 12
    f = spark.createDataFrame([("a", i, 1, 1, 2, [float(np.cos(x)), float(np.sin(x))]) for i, x in enumerate(a)], "video_id string, t int, h int, w int, ch int, px array<double>")
    m = gram.distance_matrices(f.withColumn("px", F.col("px").cast("array<float>")))
    strength = homology.loop_strength(homology.rips_h1(m)).first()
    assert strength.top > 1.2 and strength.second == 0 and strength.ratio is None
    assert np.allclose([r.len for r in homology.h0_deaths(m).collect()], 2 * np.sin(np.pi / 12), atol=1e-5)
    assert [r.i for r in homology.landmarks(m, 3).orderBy("rank").collect()][0] == 0


def test_best_loop_needs_no_table_of_pairs(spark, monkeypatch):
    """The seam of all pairs, over block borders and gaps, from frames whose pairs would not fit."""
    from cyclefold.operators import baselines

    monkeypatch.setattr(baselines, "LOOP_STARTS", 16)
    rng = np.random.default_rng(4)
    rows = [(v, t, [float(x) for x in rng.integers(0, 9, 4)]) for v in ("a", "b") for t in range(100)]
    f = spark.createDataFrame(rows, "video_id string, t int, px array<float>")
    for tmin, tmax in ((5, 60), (3, 9)):
        all_loops = ((sum((x - y) ** 2 for x, y in zip(p, q)), i, j - i, v) for v, i, p in rows for u, j, q in rows if u == v and tmin <= j - i <= tmax)
        best = sorted(all_loops)
        want = {next((v, i, n, d2) for d2, i, n, v in best if v == name) for name in "ab"}
        assert {tuple(r) for r in baselines.best_loop_of_frames(f, tmin, tmax).collect()} == want
    gaps = baselines.best_loop_of_frames(f.filter("t % 7 <> 0"), 5, 60).collect()
    assert len(gaps) == 2 and all(r.start % 7 and (r.start + r.len) % 7 for r in gaps)
    assert baselines.best_loop_of_frames(f.filter("t < 5"), 5, 60).count() == 0


def test_pairs_of_frames_in_blocks(spark, monkeypatch):
    """Any cut into blocks and tiles gives the pairs, windows and neighbours of the whole matrix."""
    from cyclefold.functions import kernels
    from cyclefold.operators import gram

    monkeypatch.setattr(gram, "BLOCK", 8)
    draw = np.random.default_rng(4)
    rows, want = [], {}
    for video, n in (("a", 37), ("b", 5), ("c", 16)):
        x = draw.normal(size=(n, 6)).astype(np.float32)
        x[n - 1] = x[1]
        rows += [(video, t, 1, 6, 1, [float(v) for v in x[t]]) for t in range(n)]
        want[video] = kernels.squared_distances(x)
    f = spark.createDataFrame(rows, "video_id string, t int, h int, w int, ch int, px array<float>")

    def agrees(found, matrices):
        got = {(r.video_id, r.i, r.j): r.d2 for r in found.collect()}
        assert set(got) == {(v, i, j) for v, m in matrices.items() for i in range(len(m)) for j in range(i + 1, len(m))}
        assert all(abs(d - matrices[v][i, j]) < 1e-9 for (v, i, j), d in got.items())

    agrees(gram.pair_distances(f), want)
    agrees(gram.pair_distances(f, 4), want)
    for d in (1, 3, 11):
        agrees(gram.window_pair_distances(f, d), {v: kernels.window_distances(m, d) for v, m in want.items()})
    got = {(r.video_id, r.i, r.rnk): r.j for r in gram.nearest_frames(f, 3).collect()}
    for v, m in want.items():
        order = np.argsort(m + np.diag(np.full(len(m), np.inf)), axis=1, kind="stable")
        assert all(got[v, i, k + 1] == order[i, k] for i in range(len(m)) for k in range(3))


def recordings(spark, shapes):
    """Drawn frames of 6 pixels by video and number of frames, the last equal to the second: (frames, {video: points})."""
    draw = np.random.default_rng(7)
    rows, points = [], {}
    for video, n in shapes:
        x = draw.normal(size=(n, 6)).astype(np.float32)
        x[n - 1] = x[1]
        rows += [(video, t, 1, 6, 1, [float(v) for v in x[t]]) for t in range(n)]
        points[video] = x
    return spark.createDataFrame(rows, "video_id string, t int, h int, w int, ch int, px array<float>"), points


def test_spanning_tree_of_frames_in_blocks(spark, monkeypatch):
    """Forests of blocks, and of groups of 16 by 16 blocks, merge to the tree of the whole matrix."""
    from cyclefold.functions import kernels
    from cyclefold.operators import gram

    monkeypatch.setattr(gram, "BLOCK", 4)
    f, points = recordings(spark, (("a", 150), ("b", 5), ("c", 2)))
    got = homology.h0_deaths_of_frames(f).collect()
    for v, x in points.items():
        found = sorted((r.rank, r.len) for r in got if r.video_id == v)
        assert [r for r, _ in found] == list(range(1, len(x)))
        assert np.allclose([d for _, d in found], kernels.h0_deaths(np.sqrt(kernels.squared_distances(x))), atol=1e-6)


def test_projection_of_long_recordings_sums_pixels(spark, monkeypatch):
    """A recording of more frames than pixels needs no matrix of its frames; distances stay, also those of zero."""
    from cyclefold.functions import kernels
    from cyclefold.operators import gram

    monkeypatch.setattr(gram, "BLOCK", 8)
    f, points = recordings(spark, (("a", 150), ("b", 5), ("c", 7)))
    short = gram.isometric(f.filter("video_id = 'b'")).collect()
    assert len(short) == 5 and all(len(r.z) == 4 for r in short)
    plan = gram.isometric(f)
    z = {(r.video_id, r.t): r.z for r in plan.collect()}
    for v, x in points.items():
        own = np.array([z[v, t] for t in range(len(x))])
        assert own.shape == (len(x), min(len(x) - 1, 6))
        assert np.allclose(kernels.squared_distances(own), kernels.squared_distances(x), atol=1e-9)
    assert {r.video_id: round(r.err, 6) for r in gram.distance_error(f, plan).collect()} == {"a": 0, "b": 0, "c": 0}
    flat = plan.withColumn("z", F.transform("z", lambda v: 2 * v))
    assert {round(r.err, 6) for r in gram.distance_error(f, flat).collect()} == {3.0}


@pytest.mark.parametrize("counted", [2**20, 4])
def test_quantile_of_windows_is_exact(spark, monkeypatch, counted):
    """By counts of leading bits alone, whatever the driver may count at once; ties and zeros too."""
    from cyclefold.functions import kernels
    from cyclefold.operators import gram

    monkeypatch.setattr(gram, "BLOCK", 8)
    monkeypatch.setattr(gram, "COUNTED", counted)
    for levels, d in ((None, 3), (2, 1)):
        draw = np.random.default_rng(3)
        x = draw.normal(size=(41, 4)) if levels is None else draw.integers(0, levels, (41, 4)).astype(float)
        f = spark.createDataFrame([("a", t, [float(v) for v in x[t]]) for t in range(41)], "video_id string, t int, px array<double>")
        m = kernels.window_distances(kernels.squared_distances(x), d)
        pairs = m[np.triu_indices(len(m), 1)]
        for q in (0.0, 0.1, 0.5, 1.0):
            assert abs(gram.window_quantile(f, d, q) - np.quantile(pairs, q)) < 1e-9
    assert gram.window_quantile(f.filter("t < 1"), 3, 0.1) is None


def test_geodesics_of_frames(spark, monkeypatch):
    """Paths by blocks of frames and starts are those of the whole matrix, over several components and equal frames."""
    from cyclefold.functions import kernels
    from cyclefold.operators import gram, period

    monkeypatch.setattr(gram, "BLOCK", 8)
    monkeypatch.setattr(period, "STARTS", 5)
    f, points = recordings(spark, (("a", 43), ("b", 5), ("c", 2), ("d", 60)))
    points["d"][20:] += 50
    points["d"][45:] += 70
    f = f.filter("video_id <> 'd'").union(spark.createDataFrame([("d", t, 1, 6, 1, [float(v) for v in x]) for t, x in enumerate(points["d"])], f.schema))
    got = {(r.video_id, r.i, r.j): r.dist for r in period.geodesics_of_frames(f, 3).collect()}
    assert len(got) == sum(len(x) * (len(x) - 1) // 2 for x in points.values())
    for v, x in points.items():
        far = kernels.geodesics(kernels.knn_graph(kernels.squared_distances(x), 3))
        assert all(abs(d - far[i, j]) < 1e-4 for (u, i, j), d in got.items() if u == v)


@pytest.mark.parametrize("block", [64, 3])
def test_isomap_of_frames(spark, monkeypatch, block):
    """The mode by products is that of the whole matrix; a frame alone and equal frames give zero."""
    from cyclefold.functions import kernels
    from cyclefold.operators import gram, period

    monkeypatch.setattr(gram, "BLOCK", 8)
    f, points = recordings(spark, (("a", 43), ("b", 5), ("c", 2)))
    same = [("d", t, 1, 6, 1, [1.0] * 6) for t in range(12)] + [("e", 0, 1, 6, 1, [1.0] * 6)]
    got = {(r.video_id, r.t): r.y for r in period.isomap1d_of_frames(f.union(spark.createDataFrame(same, f.schema)), 4, block=block).collect()}
    assert len(got) == 63 and all(got[v, t] == 0 for v, t, *_ in same)
    for v in "ab":
        y = kernels.isomap1d(kernels.squared_distances(points[v]), 4)
        own = np.array([got[v, t] for t in range(len(y))])
        assert min(np.abs(own - y).max(), np.abs(own + y).max()) < 1e-6


def test_ideal_recordings_of_which_rows_are_missing(spark):
    """Each recording's spectrum, residual and whole matrix come from the rows that it has."""
    whole = spectral.ideal_laplacian(spark, 3, 8)
    both = whole.withColumn("video_id", F.lit(1)).union(whole.filter("i % 5 = 2").withColumn("video_id", F.lit(2))).select("video_id", "i", "j", "val")
    found = {(r.video_id, r.i, r.j): r.val for r in spectral.circulant(both, 24).collect()}
    want = {(v, i, j): float(x) for v in (1, 2) for (i, j), x in np.ndenumerate(spectral.ideal_matrix(3, 8)) if x}
    assert found == want
    closed = {r.m: r["lambda"] for r in spectral.ideal_spectrum(spark, 3, 8).collect()}
    got = {(r.video_id, r.m): r["lambda"] for r in spectral.circulant_spectrum(both, 24).collect()}
    assert set(got) == {(v, m) for v in (1, 2) for m in closed} and all(abs(x - closed[m]) < 1e-9 for (_, m), x in got.items())
    resid = {(r.video_id, r.m): r.resid for r in spectral.ideal_residual(both, 3, 8).collect()}
    assert set(resid) == set(got) and max(resid.values()) < 1e-9
    off = spectral.ideal_residual(both.withColumn("val", F.when((F.col("video_id") == 2) & (F.col("i") == F.col("j")), 9.0).otherwise(F.col("val"))), 3, 8).collect()
    assert all((r.resid > 0.5) == (r.video_id == 2) for r in off)


def rows_sent(df):
    """Rows that all exchanges of a plan wrote."""
    df.collect()
    total, todo = 0, [df._jdf.queryExecution().executedPlan()]
    while todo:
        node = todo.pop()
        name = node.getClass().getSimpleName()
        if name == "AdaptiveSparkPlanExec":
            todo.append(node.executedPlan())
        elif name.endswith("QueryStageExec"):
            todo.append(node.plan())
        else:
            if name == "ShuffleExchangeExec":
                total += node.metrics().apply("shuffleRecordsWritten").value()
            todo += [node.children().apply(k) for k in range(node.children().size())]
    return total


def test_copies_of_a_frame_do_not_grow_with_the_recording(spark, monkeypatch):
    """A frame is sent once for each region, of which there are as many for any length; what comes of two regions is gathered."""
    from cyclefold.operators import gram

    monkeypatch.setattr(gram, "BLOCK", 2)
    monkeypatch.setattr(gram, "GATHERED", 64)
    f, _ = recordings(spark, (("a", 300),))
    regions = 4 * spark.sparkContext.defaultParallelism**0.5
    assert rows_sent(gram.pair_distances(f)) < 300 * (regions + 2)
    assert rows_sent(gram.nearest_frames(f, 2)) < 300 * (3 * regions + 2)


@pytest.mark.parametrize("held", [2**24, 1])
def test_regions_of_many_blocks_have_all_pairs(spark, monkeypatch, held):
    """Pairs, windows, tiles and neighbours of regions of many blocks, and where a task may hold one block only, are those of the matrix."""
    from cyclefold.functions import kernels
    from cyclefold.operators import gram

    monkeypatch.setattr(gram, "BLOCK", 4)
    monkeypatch.setattr(gram, "HELD", held)
    monkeypatch.setattr(gram, "GATHERED", 8)
    f, points = recordings(spark, (("a", 90), ("b", 5), ("c", 2)))
    matrices = {v: ((x[:, None].astype(float) - x[None]) ** 2).sum(axis=2) for v, x in points.items()}

    def agrees(found, matrices):
        rows = [(r.video_id, r.i, r.j, r.d2) for r in found.collect()]
        assert sorted(r[:3] for r in rows) == [(v, i, j) for v, m in matrices.items() for i in range(len(m)) for j in range(i + 1, len(m))]
        assert all(abs(d - matrices[v][i, j]) < 1e-9 for v, i, j, d in rows)

    agrees(gram.pair_distances(f), matrices)
    agrees(gram.pair_distances(f, 4), matrices)
    agrees(gram.window_pair_distances(f, 11), {v: kernels.window_distances(m, 11) for v, m in matrices.items()})
    got = {(r.video_id, r.i, r.rnk): r.j for r in gram.nearest_frames(f, 3).collect()}
    want = {(v, i, k + 1): j for v, m in matrices.items() for i in range(len(m)) for k, j in enumerate(np.argsort(m[i] + np.where(np.arange(len(m)) == i, np.inf, 0), kind="stable")[: min(3, len(m) - 1)])}
    assert got == want
    whole = {(r.video_id, r.i, r.j): r.g for r in gram.centred_of_frames(f).collect()}
    for v, m in matrices.items():
        g = -0.5 * (m - m.mean(0) - m.mean(1)[:, None] + m.mean())
        assert all(abs(whole.pop((v, i, j)) - g[i, j]) < 1e-9 for i in range(len(m)) for j in range(i, len(m)))
    assert not whole


def test_values_beside_frames_need_no_join_with_pairs(spark):
    """Row means and sums go to the frames, never to the rows of pairs."""
    from cyclefold.operators import baselines, gram

    f, _ = recordings(spark, (("a", 40),))
    for df in (gram.centred_of_frames(f), baselines.jump_table_of_frames(f, 0.5)):
        above = df._jdf.queryExecution().executedPlan().toString().split("MapInArrow")[0]
        assert "Join" not in above
