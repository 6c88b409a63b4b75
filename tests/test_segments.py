from cyclefold.plans import regimes


def test_full_segments_hold_every_frame(spark):
    for n, starts in ((240, [0, 100, 120]), (220, [0, 100]), (221, [0, 100, 101]), (120, [0]), (50, [0]), (121, [0, 1])):
        f = spark.range(n).selectExpr("'a' video_id", "cast(id as int) t", "id at")
        out = {}
        for r in regimes.full_segments(f, 120, 20).collect():
            out.setdefault(r.video_id, []).append((r.t, r.at))
        assert [min(out[f"a#{k}"])[1] for k in range(len(starts))] == starts and len(out) == len(starts)
        for k, s in enumerate(starts):
            assert sorted(out[f"a#{k}"]) == [(i, s + i) for i in range(min(n, 120))]


def test_last_frames_vote(spark):
    from cyclefold.queries import QUERIES

    got = QUERIES["fold_segments"](spark, "/root/testdata/sf0.001").collect()
    assert len(got) == 40 and all(r.voted and r.close for r in got)


def test_each_video_takes_the_form_of_its_size(spark):
    """Short, long and large recordings in one call; no group holds the distances of more than the local frames."""
    import numpy as np

    from cyclefold.config import FoldConfig
    from cyclefold.plans import pipeline

    schema = "video_id string, t int, h int, w int, ch int, px array<float>"
    draw = np.random.default_rng(1)
    waves = draw.normal(size=(5, 24))

    def rows(name, n, width):
        a = 2 * np.pi * np.arange(n) / 20
        px = np.stack([np.cos(a), np.sin(a), np.cos(2 * a), np.sin(2 * a)], axis=1) @ waves[:4, :width] + draw.normal(0, 0.02, (n, width))
        return [(name, t, 1, width, 1, [float(x) for x in p]) for t, p in enumerate(px)]

    f = spark.createDataFrame(rows("short", 100, 12) + rows("long", 330, 12) + rows("large", 100, 24), schema)
    config = FoldConfig(pyramid_level=1, max_n=60, M=20, local_frames=150, local_px=16, overlap=50)
    assert {r.video_id: r.regime for r in regimes.planned(f, 150, 16).collect()} == {"short": "many", "long": "endless", "large": "huge"}
    got = pipeline.fold(f, config).collect()
    for name, width in (("short", 12), ("long", 12), ("large", 24)):
        own = sorted((r.j, r.px) for r in got if r.video_id == name)
        assert [j for j, _ in own] == list(range(20)) and {len(p) for _, p in own} == {width}
        a = 2 * np.pi * np.arange(20) / 20
        want = np.stack([np.cos(a), np.sin(a), np.cos(2 * a), np.sin(2 * a)], axis=1) @ waves[:4, :width]
        px = np.array([p for _, p in own])
        assert min(np.sqrt(((np.roll(x, s, axis=0) - want) ** 2).mean()) for x in (px, px[::-1]) for s in range(20)) < 0.3, name
    parts = regimes.full_segments(f.filter("video_id = 'long'"), config.local_frames, config.overlap)
    assert parts.groupBy("video_id").count().agg({"count": "max"}).first()[0] == 150
