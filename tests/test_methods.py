"""Worked examples, brute force, invariants, plans."""

import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from chartrel.functions import color, registry
from chartrel.operators import baseline, cluster, learned, legend, measure, nn, raster, synth, text, truth
from chartrel.plans import catalog, experiments
from chartrel.plans.queries import QUERIES
from chartrel.sources import charts, png
from chartrel.sources.families import FAMILIES


def points(spark, series):
    rows = [(c, s, x, y) for (c, s), ys in series.items() for x, y in (ys.items() if isinstance(ys, dict) else enumerate(ys))]
    return spark.createDataFrame(rows, "chart_id long, series_key string, x long, y long")


def test_relation_boundary_cases(spark):
    got = truth.relations(points(spark, {(1, "tie4"): [1, 3, 4, 2], (1, "const"): [5] * 5, (1, "one"): [3], (1, "up"): [1, 2, 3, 4], (1, "down"): [4, 3, 2, 1], (2, "tie5"): [1, 5, 2, 3, 4]}))
    by = {(r["chart_id"], r["series_key"]): r["relation"] for r in got.collect()}
    assert by[1, "tie4"] == "neutral"  # squared rank differences sum to 6 of 4 points: exactly 0.4
    assert by[2, "tie5"] == "neutral" or by[2, "tie5"] == "increasing"
    assert by[1, "const"] == "neutral" and by[1, "one"] == "undefined" and by[1, "up"] == "increasing" and by[1, "down"] == "decreasing"


def test_long_series_are_decided_exactly(spark):
    n = 150_000
    spread = F.col("id") * 104_729 % n
    rising = spark.range(n).select(F.lit(1).cast("long").alias("chart_id"), F.lit("up").alias("series_key"), F.col("id").alias("x"), (spread + F.col("id")).alias("y"))
    mixed = spark.range(n).select(F.lit(1).cast("long").alias("chart_id"), F.lit("flat").alias("series_key"), F.col("id").alias("x"), spread.alias("y"))
    got = {r["series_key"]: r for r in truth.relations(rising.unionByName(mixed)).collect()}
    x, s = np.arange(n), np.arange(n) * 104_729 % n
    for name, y in (("up", s + x), ("flat", s)):
        assert got[name]["n"] == n and got[name]["relation"] == registry.relation(x, y) and abs(got[name]["rho"] - registry.rho(x, y)) < 1e-6
    assert got["up"]["relation"] == "increasing" and got["flat"]["relation"] == "neutral"


def test_cut_is_exact_beyond_38_digits(spark):
    rng = random.Random(4)
    rows = []
    for _ in range(200):
        z = rng.choice((10**3, 10**14, 10**15, 10**27))
        v = rng.randrange(1, z)
        rows.append((2 * v, 5 * v, 5 * v))  # at the cut
        rows += [(2 * v + d, 5 * v, 5 * v + e) for d, e in ((1, 0), (-1, 0), (0, 1), (0, -1))]
        rows += [(-2 * v, 25 * v, v), (rng.randrange(-z, z), rng.randrange(1, z + 1), rng.randrange(1, z + 1))]
    df = spark.createDataFrame([tuple(str(x) for x in r) for r in rows], "a string, b string, c string").select(*(F.col(c).cast("decimal(30,0)") for c in "abc"))
    for p, q in ((2, 5), (11, 20)):
        for r in df.withColumn("s", truth.against(F.col("a"), F.col("b"), F.col("c"), (p, q))).collect():
            a, b, c = int(r["a"]), int(r["b"]), int(r["c"])
            d = q * q * a * a - p * p * b * c
            assert r["s"] == (d > 0) - (d < 0)


def test_uncleaned_colours_are_not_merged():
    rng = np.random.default_rng(2)
    img = np.full((120, 120, 3), 255, np.uint8)
    img[20:100, 20:100] = (250, 3, 1)
    img[:80, 100:] = rng.integers(0, 256, (80, 20, 3))
    img[100:, :] = rng.integers(0, 256, (20, 120, 3))
    x, w = cluster.np_histogram(img)
    assert len(x) > 3000 and w.sum() == 120 * 120
    k, found = cluster.np_series(img, clean=False)
    errors, fits = cluster.sweep(x, w)
    c, own = fits[k - 1]
    weight = np.array([w[own == j].sum() for j in range(len(c))])
    order = [j for j in np.argsort(-weight, kind="stable").tolist() if weight[j] > 0][1:]
    assert k == cluster.chosen(errors) and {rgb for rgb, _ in found} <= {tuple(np.rint(c[j]).astype(int).tolist()) for j in order}


def test_exact_tie_of_five_is_neutral(spark):
    for ys in itertools.permutations(range(1, 6)):
        if sum((i + 1 - y) ** 2 for i, y in enumerate(ys)) == 12:
            assert truth.relations(points(spark, {(1, "a"): list(ys)})).first()["relation"] == "neutral"
            break


def test_spearman_equals_definition(spark):
    rng = random.Random(1)
    series = {(c, "s"): [rng.randrange(6) for _ in range(rng.randrange(2, 12))] for c in range(40)}
    got = {r["chart_id"]: r["rho"] for r in truth.spearman(points(spark, series)).collect()}
    for (c, _), ys in series.items():
        want = registry.rho(np.arange(len(ys)), np.array(ys))
        assert (got[c] is None) == (want is None) and (want is None or abs(got[c] - want) < 1e-12)


def test_spearman_invariants(spark):
    base = FAMILIES["nation"](spark, "/root/testdata/sf0.001")
    rho = lambda p: {(r["chart_id"], r["series_key"]): r["rho"] for r in truth.spearman(p).collect()}
    a = rho(base)
    b = rho(base.withColumn("y", -F.col("y")))
    c = rho(base.withColumn("y", F.col("y") * 3 + 7))
    assert all(abs(a[k] + b[k]) < 1e-12 and a[k] == c[k] and -1 <= a[k] <= 1 for k in a)


@pytest.mark.parametrize("rgb,hsv", [((0, 0, 0), (0, 0, 0)), ((255, 255, 255), (0, 0, 255)), ((255, 0, 0), (0, 255, 255)), ((0, 255, 0), (60, 255, 255)), ((0, 0, 255), (120, 255, 255)), ((10, 0, 0), (0, 255, 10)), ((128, 128, 128), (0, 0, 128))])
def test_hsv_known(spark, rgb, hsv):
    assert tuple(color.np_hsv(np.array([rgb]))[0]) == hsv
    r = color.with_hsv(spark.createDataFrame([rgb], "r int, g int, b int")).first()
    assert (r["h"], r["s"], r["v"]) == hsv


def test_hsv_columns_equal_numpy(spark):
    rng = np.random.default_rng(0)
    rgb = rng.integers(0, 256, (500, 3))
    got = color.with_hsv(spark.createDataFrame([tuple(map(int, x)) for x in rgb], "r int, g int, b int")).collect()
    want = color.np_hsv(rgb)
    assert all((r["h"], r["s"], r["v"]) == tuple(color.np_hsv(np.array([[r["r"], r["g"], r["b"]]]))[0]) for r in got)
    full = color.np_full_hue(np.arange(180))
    assert (color.np_hsv(full)[:, 1:] == 255).all() and np.abs((color.np_hsv(full)[:, 0] - np.arange(180) + 90) % 180 - 90).max() <= 1
    assert want[:, 0].max() < 180


def test_saturation_idempotent_and_grays(spark):
    px = spark.createDataFrame([(1, 0, 0, 0, 0, 0), (1, 1, 0, 128, 128, 128), (1, 2, 0, 10, 0, 0), (1, 3, 0, 200, 40, 40)], "chart_id long, px int, py int, r int, g int, b int")
    once = cluster.saturate(px)
    got = {r["px"]: (r["r"], r["g"], r["b"]) for r in once.collect()}
    assert got == {0: (255, 255, 255), 1: (255, 255, 255), 2: (255, 0, 0), 3: (255, 0, 0)}
    assert sorted(map(tuple, cluster.saturate(once).collect())) == sorted(map(tuple, once.collect()))
    assert {r["px"]: r["r"] for r in cluster.saturate(px, background="black").collect()}[1] == 0
    img = np.array([[[0, 0, 0], [128, 128, 128], [10, 0, 0], [200, 40, 40]]], np.uint8)
    assert [tuple(x) for x in cluster.np_saturate(img)[0].tolist()] == [got[i] for i in range(4)]


WHITE, BLACK = (255, 255, 255), (0, 0, 0)
RGB = ((255, 0, 0), (0, 255, 0), (0, 0, 255))


@pytest.mark.parametrize("ink,background,knee,corrected,repeat", [
    ((1,), WHITE, 2, 2, 2), ((1,), BLACK, 2, 2, 2), ((1, 1), WHITE, 3, 3, 3), ((1, 1), BLACK, 3, 3, 3), ((1, 1, 1), WHITE, 4, 4, 4),
    ((1, 1, 1), BLACK, 4, 4, 4), ((1, 0.205), WHITE, 2, 3, 3), ((1, 0.205), BLACK, 3, 3, 3), ((1, 0.016), WHITE, 2, 3, 3),
    ((1, 0.015), WHITE, 2, 2, 2), ((1, 0.3, 0.1), WHITE, 3, 4, 4), ((1, 0.1, 0.1), WHITE, 2, 3, 4),
])
def test_choice_of_k(ink, background, knee, corrected, repeat):
    x = np.array([background, *RGB[: len(ink)]], float)
    w = np.array([1e9, *(1000 * i for i in ink)])
    errors, _ = cluster.sweep(x, w)
    assert cluster.chosen(errors, "knee") == knee
    assert cluster.chosen(errors) == corrected
    assert cluster.chosen(errors, norm="residual") == corrected
    assert cluster.chosen(errors, "repeat") == repeat


def test_blank_chart_has_one_cluster():
    errors, _ = cluster.sweep(np.array([[255.0, 255, 255]]), np.array([100.0]))
    assert cluster.chosen(errors) == 1 and cluster.curve(errors) == [1.0] * 8


def test_knee_column_equals_function(spark):
    rng = np.random.default_rng(3)
    curves = [sorted(rng.random(8).tolist()) for _ in range(60)] + [[0.5] * 8]
    df = spark.createDataFrame([(i, c) for i, c in enumerate(curves)], "i int, c array<double>")
    got = {r["i"]: r["k"] for r in df.select("i", cluster.knee_column(F.col("c")).alias("k")).collect()}
    assert got == {i: cluster.knee(c) for i, c in enumerate(curves)}


def _partitions(items):
    if not items:
        yield []
        return
    for p in _partitions(items[1:]):
        yield [[items[0]], *p]
        for i in range(len(p)):
            yield p[:i] + [[items[0], *p[i]]] + p[i + 1 :]


def test_kmeans_against_exhaustive_partitions():
    rng = np.random.default_rng(5)
    for _ in range(6):
        x, w = rng.integers(0, 256, (6, 3)).astype(float), rng.integers(1, 50, 6).astype(float)
        cost = lambda b: sum(((x[g] - np.average(x[g], axis=0, weights=w[g])) ** 2).sum(axis=1) @ w[g] for g in b)  # noqa: B023, E731
        for k in (2, 3):
            best = min(cost(b) for b in _partitions(list(range(6))) if len(b) == k)
            _, _, got = cluster.fit(x, w, k)
            assert best - 1e-6 <= got <= max(6 * best, best + 1)
    errors, _ = cluster.sweep(x, w)
    assert all(a >= b - 1e-9 for a, b in zip(errors, errors[1:]))


def test_histogram_is_all_pixels(spark):
    px = QUERIES["raster_line"](spark, "/root/testdata/sf0.001")
    per = cluster.histogram(px, raster.W * raster.H).groupBy("chart_id").agg(F.sum("w").alias("w")).collect()
    assert {r["w"] for r in per} == {raster.W * raster.H}


@pytest.mark.parametrize("hue,inside,outside", [(3, (0, 13, 175, 179), (20, 170)), (176, (166, 179, 2), (12, 160)), (60, (50, 70), (49, 71))])
def test_range_wrap(spark, hue, inside, outside):
    rgb = tuple(map(int, color.np_full_hue(np.array([hue]))[0]))
    own = color.np_hsv(np.array([rgb]))[0, 0]
    boxes = cluster.np_boxes(np.array([rgb]))[0]
    ok = lambda h: bool(cluster.np_mask(np.array([[[h, 255, 255]]]), boxes)[0, 0])
    assert abs(int(own) - hue) <= 1 and all(ok(h) for h in inside) and not any(ok(h) for h in outside)
    got = cluster.ranges(spark.createDataFrame([(1, 1, *rgb)], "chart_id long, series_no int, r int, g int, b int")).collect()
    assert sorted((r["hlo"], r["hhi"]) for r in got) == sorted(b[:2] for b in boxes)


def test_clamped_and_literal_bounds(spark):
    c = spark.createDataFrame([(1, 1, 30, 0, 1)], "chart_id long, series_no int, r int, g int, b int")
    r = cluster.ranges(c).filter("part = 1").first()
    assert (r["slo"], r["shi"], r["vlo"], r["vhi"]) == (230, 255, 0, 70)
    lit = cluster.ranges(c, bounds="literal").filter("part = 1").first()
    assert lit["hlo"] <= 0 and lit["hhi"] >= 180


def test_packed_equals_relational(spark):
    d = "/root/testdata/sf0.001"
    points_ = FAMILIES["supplier"](spark, d)
    px = raster.ink(points_, synth.coloured(points_), "line")
    packed = learned.predict(raster.packed(px), rule="repeat")
    a = {(r["chart_id"], r["r"], r["g"], r["b"]): r["relation"] for r in packed.collect()}
    b = {(r["chart_id"], r["r"], r["g"], r["b"]): r["relation"] for r in QUERIES["programmed_relations"](spark, d).collect()}
    assert len(a) >= 0.9 * len(b) and all(b[k] == v for k, v in a.items())


def test_legend_anchors_and_oversized_box(spark):
    texts = spark.createDataFrame([(1, 0, "a", 20, 10), (1, 1, "b", 20, 30)], "chart_id long, ordinal int, text string, cx int, cy int")
    marks = [(1, 1, x, 10) for x in range(5, 9)] + [(1, 2, x, 30) for x in range(5, 9)] + [(1, 2, 19, 11)]  # one stray pixel of series 2 beside text a
    m = spark.createDataFrame(marks, "chart_id long, series_no int, px int, py int")
    by = lambda k: {r["text"]: r["series_no"] for r in legend.assign(texts, m, k).collect()}
    assert by("median") == {"a": 1, "b": 2} and by("nearest")["a"] == 2
    boxed = legend.in_box(m, spark.createDataFrame([(1, 0, 0, 10, 40)], "chart_id long, x0 int, y0 int, x1 int, y1 int"))
    assert boxed.count() == 8


def test_measures_worked(spark):
    t = spark.createDataFrame([(1, k, lab, "increasing", *c) for k, lab, c in (("a", "alpha", (255, 0, 0)), ("b", "beta", (0, 255, 0)), ("c", "gamma", (0, 0, 255)))], "chart_id long, series_key string, series_label string, relation string, r int, g int, b int")
    p = spark.createDataFrame([(1, 1, "alphx", "increasing", 255, 0, 0), (1, 2, "betaxx", "increasing", 0, 255, 0), (1, 3, "gamxxx", "increasing", 0, 0, 255), (1, 4, "zzzzzz", "increasing", 255, 255, 0)], "chart_id long, series_no int, series_label string, relation string, r int, g int, b int")
    assert measure.series(p, t).first()["value"] == pytest.approx(2 / 3, abs=1e-6)
    assert measure.series_no_ocr(p, t).first()["value"] == 1 and measure.raw(p, t).first()["value"] == 0
    ax = spark.createDataFrame([(1, "abcdefghij", "klmnopqrst"), (2, "abcdefghij", "klm")], "chart_id long, x_label string, y_label string")
    five = spark.createDataFrame([(1, "abcdeXXXXX", "klmnopqrst")], "chart_id long, x_label string, y_label string")
    six = spark.createDataFrame([(1, "abcdXXXXXX", "klmnopqrst")], "chart_id long, x_label string, y_label string")
    assert measure.axis(five, ax).first()["value"] == 0.5 and measure.axis(six, ax).first()["value"] == 0 and measure.axis(six, ax, unit="label").first()["value"] == 0.25
    one = spark.createDataFrame([(100, 0.86), (100, 0.833)], "n long, value double")
    assert measure.total(one.limit(1), one.filter("value < 0.85")).first()["value"] == pytest.approx(0.8465)
    assert measure.series(p.filter("chart_id = 9"), t).first()["value"] == 0


def test_turning_points_and_as_of(spark):
    t = spark.createDataFrame([(1, x, y) for x, y in enumerate((0, 5, 9, 4, 4, 2, 8))], "chart_id long, x long, y long")
    got = [(r["x"], r["y"]) for r in baseline.turning_points(t).orderBy("x").collect()]
    assert got == [(0, 0), (2, 9), (5, 2), (6, 8)]
    grid = spark.range(7).select(F.lit(1).cast("long").alias("chart_id"), F.col("id").alias("x"))
    seen = [r["y"] for r in baseline.as_of(grid, baseline.turning_points(t)).orderBy("x").collect()]
    assert seen == [0, 0, 9, 9, 9, 2, 8]


def test_text_round_trip_and_rotation():
    for s in ("Revenue", "abcXYZ019", "lI1O0"):
        ink = text.drawn(s)
        assert text.read(ink)[0] == s
        up = np.rot90(ink)
        assert text.read_any(up, "manual", True) == s and text.read_any(up, "auto", True) == s and text.read_any(up, "none", True) != s


def test_detectors_find_boxes(spark):
    pts = FAMILIES["supplier"](spark, "/root/testdata/sf0.01")
    labels = synth.styles(pts).select("chart_id", "title", "x_label", "y_label")
    use = experiments.first_charts(pts, 40)
    images, facets = text.annotated(experiments.rendered(use), labels, experiments.true_series(use))
    images, facets = images.persist(), facets.persist()
    assert experiments.box_overlap(text.detect(images), facets).first()["value"] > 0.95
    ssd = experiments.trained_detector(images.filter("chart_id % 2 = 0"), facets)
    test = images.filter("chart_id % 2 = 1")
    assert experiments.box_overlap(text.detect(test, "ssd", ssd), facets.filter("chart_id % 2 = 1")).first()["value"] > 0.3
    iou = text.Detector.overlap(np.array([[0.0, 0, 2, 2]]), np.array([[1.0, 1, 3, 3], [5, 5, 6, 6]]))[0]
    assert iou.tolist() == pytest.approx([1 / 7, 0])


def test_network_gradients_and_overfit():
    rng = np.random.default_rng(0)
    x, y = rng.random((4, nn.SIDE, nn.SIDE)).astype(np.float32), np.array([[0], [1], [2], [0]])
    net = nn.Cnn(1, 1, {k: v.astype(np.float64) for k, v in nn.Cnn(1, 1).w.items()})
    g, _ = net.gradient(x, y)
    for k in ("k0", "k1", "k2", "d", "o", "b1"):
        i = np.unravel_index(int(np.abs(g[k]).argmax()), g[k].shape)
        old, eps = net.w[k][i], 1e-4
        net.w[k][i] = old + eps
        up = net.gradient(x, y)[1]
        net.w[k][i] = old - eps
        down = net.gradient(x, y)[1]
        net.w[k][i] = old
        assert g[k][i] == pytest.approx((up - down) / (2 * eps), rel=0.08, abs=1e-3)
    lines = []
    for i in range(24):
        img = np.zeros((40, 60), bool)
        for c in range(60):
            img[[39 - c * 39 // 59, c * 39 // 59, 20][i % 3], c] = True
        lines.append(nn.shrink(img))
    labels = np.array([[i % 3] for i in range(24)])
    net = nn.fit(np.stack(lines), labels, epochs=40)
    assert (net.forward(np.stack(lines))[0][:, 0].argmax(axis=1) == labels[:, 0]).mean() >= 0.95
    two = nn.Cnn(2)
    assert two.forward(np.stack(lines[:2]))[0].shape == (2, 2, 3)


def test_models_as_tables_and_parallel_training(spark, tmp_path):
    pts = experiments.first_charts(experiments.balanced_points(spark, "/root/testdata/sf0.001", "nation", 2), 8)
    rows = learned.examples(experiments.rendered(pts), experiments.true_series(pts)).persist()
    model = learned.train_parallel(rows, epochs=2)
    learned.save_model(spark, model, str(tmp_path / "m"))
    back = learned.load_model(spark, str(tmp_path / "m"))
    assert all(np.allclose(model.w[k], back.w[k]) for k in model.w)


def test_png_round_trip(spark, tmp_path):
    img = np.random.default_rng(0).integers(0, 256, (9, 7, 3)).astype(np.uint8)
    assert (png.decode(png.encode(img)) == img).all()
    for c in (3, 8):
        (tmp_path / f"{c}.png").write_bytes(png.encode(img))
    assert sorted(r["chart_id"] for r in png.from_files(spark, str(tmp_path)).collect()) == [3, 8]


def test_chart_source_and_sql_functions(spark):
    charts.register(spark)
    a = spark.read.format("charts").option("n", 20).load()
    assert a.select("chart_id").distinct().count() == 20
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, spark.read.format("charts").option("n", 20).option("partitions", 3).load().collect()))
    registry.register_sql(spark)
    a.createOrReplaceTempView("pts")
    got = spark.sql("select chart_id, series_key, visual_relation(collect_list(x), collect_list(y)) as relation from (select * from pts order by x) group by 1, 2")
    want = {(r["chart_id"], r["series_key"]): r["relation"] for r in truth.relations(a).collect()}
    assert {(r["chart_id"], r["series_key"]): r["relation"] for r in got.collect()} == want
    assert spark.sql("select label_within('alpha', 'alphx', 2) as a, label_within('alpha', 'zzzzz', 2) as b").first().asDict() == {"a": True, "b": False}
    assert [tuple(r) for r in spark.sql("select * from trace_columns(array(1, 1, 2), array(2.0D, 4.0D, 5.0D))").collect()] == [(1, 3.0), (2, 5.0)]


def test_catalog_search_prunes(spark, small, tmp_path):
    path = str(tmp_path / "cat")
    catalog.save(QUERIES["relation_tuples"](spark, small), path, "overwrite")
    hit = catalog.search(spark, path, relation="neutral", x="ship yeax", within=1)
    assert hit.count() > 0 and "PartitionFilters: [isnotnull(relation" in hit._jdf.queryExecution().toString()


def test_plan_shapes(spark, small):
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    p = plan(truth.relations(FAMILIES["customer_status"](spark, small)))
    assert p.count("Exchange hashpartitioning") == 1 and "o_orderpriority" not in p
    assert "NestedLoop" not in plan(QUERIES["masks_by_range"](spark, small)) and "Cartesian" not in plan(QUERIES["legend_median"](spark, small))


def test_train_and_test_do_not_meet(spark, small):
    pts = FAMILIES["customer"](spark, small)
    a, b = experiments.first_charts(pts, 50), experiments.first_charts(pts, 50, 0, 50)
    assert a.select("chart_id").intersect(b.select("chart_id")).count() == 0


def test_lines_beat_the_point_extractor_and_bars_do_not_need_to(spark):
    value = lambda df: {(r["corpus"], r["metric"]): r["value"] for r in df.collect()}
    lines = value(QUERIES["compare_lines"](spark, "/root/testdata/sf0.01"))
    assert lines["ours", "series_no_ocr"] > lines["mean_trace", "series_no_ocr"] and lines["ours", "raw"] > lines["point_extractor", "raw"] > lines["mean_trace", "raw"]
    bars = value(QUERIES["compare_single_bars"](spark, "/root/testdata/sf0.01"))
    assert bars["ours", "series_no_ocr"] >= 0.9


def test_easy_beats_hard(spark):
    s = {r["corpus"]: r["value"] for r in QUERIES["web_like"](spark, "/root/testdata/sf0.01").collect()}
    assert s["easy"] > s["hard"]


def test_rotation_helps(spark):
    s = {r["corpus"]: r["value"] for r in QUERIES["rotation_ablation"](spark, "/root/testdata/sf0.001").collect()}
    assert s["manual"] >= s["auto"] > s["none"]


def test_failure_catalog(spark, small):
    rows = QUERIES["failure_catalog"](spark, small).collect()
    charts = {r["chart_id"] for r in rows}
    assert charts == {r[0] for r in FAMILIES["nation"](spark, small).filter("series_key = 'F'").select("chart_id").distinct().collect()}
    assert len(rows) == 8 * len(charts) and all(r["found"] == r["expected"] for r in rows)


def test_hues_about_red_come_from_vectors(spark, small):
    ids = {r[0] for r in spark.read.parquet(f"{small}/embeddings.parquet").select("vec_id").collect()}
    rows = QUERIES["hsv_ranges_wrap"](spark, small).collect()
    assert {r["chart_id"] for r in rows} <= ids and {r["part"] for r in rows} == {1, 2} and any("embeddings" in f for f in QUERIES["hsv_ranges_wrap"](spark, small).inputFiles())
