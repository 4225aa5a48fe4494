"""Worked examples, gadgets with closed forms, and identities between methods."""

import random

import pytest
from pyspark.sql import functions as F

from catchment.functions import influence, metrics
from catchment.operators import arcs, circles, gadgets, grid, prune, regions, stateful, strips, surface, sweep
from catchment.plans import planner
from catchment.sources import points

BOXES = "oid long, xl long, xh long, yl long, yh long, weight long"
LABEL = ["x0", "x1", "y0", "y1"]


def squares(spark, rows):
    return circles.canonical(spark.createDataFrame([(*r, 1) for r in rows], BOXES))


@pytest.fixture(scope="module")
def four(spark):
    return squares(spark, [(1, 6, 74, -9, 59), (2, 46, 110, -11, 53), (3, -13, 29, 28, 70), (4, 14, 60, 39, 85)])


@pytest.fixture(scope="module")
def moving(spark):
    return squares(spark, [(1, 0, 6, 4, 10), (2, 2, 10, 6, 14), (3, 4, 13, -1, 8), (4, 6, 15, 9, 18)])


def test_four_clients(four):
    found = regions.cost_measures(four).first()
    assert (found["m"], found["k_all"], found["k"], found["r"], found["lambda_max"], found["sum_rnn"]) == (49, 21, 11, 12, 3, 19)
    sets = {tuple(r["rnn"]) for r in sweep.label_changed_sets(four).collect()}
    assert sets == {(1,), (2,), (3,), (4,), (1, 2), (1, 3), (1, 4), (3, 4), (1, 3, 4), (1, 2, 4)}


def test_connected_pairs(spark, four):
    boxes = spark.createDataFrame([(1, 6, 74, -9, 59), (2, 46, 110, -11, 53), (3, -13, 29, 28, 70), (4, 14, 60, 39, 85)], "oid long, xl long, xh long, yl long, yh long")
    extra = influence.edge_boxes(boxes, spark.createDataFrame([(1, 2), (1, 4), (2, 4)], "a long, b long"))
    heat = sweep.label_changed(four.withColumn("pairs", F.lit(0).cast("long")), ("n", "pairs"), extra=extra)
    sets = sweep.label_changed_sets(four).select("x0", "y0", "rnn").join(heat.select("x0", "y0", "pairs"), ["x0", "y0"])
    rows = sets.collect()
    assert all(r["pairs"] == sum(a in r["rnn"] and b in r["rnn"] for a, b in ((1, 2), (1, 4), (2, 4))) for r in rows)
    assert [tuple(r["rnn"]) for r in rows if r["pairs"] == 3] == [(1, 2, 4)]


def test_changed_intervals_example(moving):
    labels = sweep.label_changed_sets(moving).orderBy("x0", "y0").collect()
    got = [(r["x0"], r["y0"], r["y1"], tuple(r["rnn"])) for r in labels]
    assert got == [(0, 4, 10, (1,)), (2, 6, 10, (1, 2)), (2, 10, 14, (2,)), (4, -1, 4, (3,)), (4, 4, 6, (1, 3)), (4, 6, 8, (1, 2, 3)), (6, 6, 8, (2, 3)), (6, 8, 9, (2,)), (6, 9, 14, (2, 4)), (6, 14, 18, (4,)), (10, 8, 9, ())]
    merged = {(r["x"], r["lo"], r["hi"]) for r in sweep.changed_intervals(moving).collect()}
    assert (6, 4, 18) in merged
    status = [(r["y"], r["oid"]) for r in sweep.line_status(moving).filter("slab = 2").orderBy("pos").collect()]
    assert status == [(-1, 3), (4, 1), (6, 2), (8, 3), (10, 1), (14, 2)]


def test_boundary_set_change(spark):
    three = squares(spark, [(1, 0, 10, 0, 10), (2, 2, 6, 2, 5), (3, 2, 6, 5, 9)])
    r = regions.cost_measures(three).first()
    assert (r["m"], r["k_all"], r["k"], r["r"]) == (12, 6, 3, 4)


@pytest.mark.parametrize("make, want", [
    (lambda s: gadgets.diagonal_squares(s, 2), (9, 5, 3, 4, 4)),
    (lambda s: gadgets.diagonal_squares(s, 5), (81, 41, 21, 22, 45)),
    (lambda s: gadgets.disjoint_squares(s, 5), (81, 5, 5, 6, 5)),
    (lambda s: gadgets.comb_squares(s, 5), (33, 21, 16, 12, 16)),
])
def test_gadgets(spark, make, want):
    g = circles.canonical(make(spark))
    r = regions.cost_measures(g).first()
    assert (r["m"], r["k_all"], r["k"], r["r"], r["sum_rnn"]) == want
    assert regions.euler_region_count(g).first()["r"] == r["r"]
    assert r["r"] - 1 <= r["k"] <= 14 * r["r"]


def test_distinctness(spark):
    count = lambda values: regions.region_table(regions.subregions(circles.canonical(gadgets.distinctness_squares(spark, values)))).count()
    assert count([5, 1, 9, 3, 7]) == 5
    assert count([5, 1, 9, 3, 3]) == 4


def test_coincident_and_empty(spark):
    five = squares(spark, [(i, 0, 4, 0, 4) for i in range(5)])
    assert sweep.label_changed(five).select("n").collect()[0][0] == 5
    none = squares(spark, [(1, 3, 3, 3, 3)])
    assert none.count() == 0 and sweep.label_changed(none).count() == 0
    assert regions.region_table(regions.subregions(none)).count() == 1


def sample(spark, seed, n=30, n_f=5, extent=60):
    rng = random.Random(seed)
    c = [(i, rng.randrange(extent), rng.randrange(extent), 1, str(i % 3)) for i in range(n)]
    f = [(i, rng.randrange(extent), rng.randrange(extent), 2) for i in range(n_f)]
    return spark.createDataFrame(c, points.CLIENTS), spark.createDataFrame(f, points.FACILITIES)


@pytest.mark.parametrize("seed", [1, 2])
def test_methods_agree(spark, seed):
    c, f = sample(spark, seed)
    g = circles.canonical(circles.nn_circles(c, f, "linf")).persist()
    b1, b4 = grid.label_side_grid(g), grid.superimpose(g)
    assert b1.exceptAll(b4).isEmpty() and b4.exceptAll(b1).isEmpty()
    assert b1.exceptAll(grid.label_side_grid(g, index="none")).isEmpty()
    full, part = sweep.label_all_pairs(g).select(*LABEL, "n"), sweep.label_changed(g).select(*LABEL, "n")
    assert part.exceptAll(full).isEmpty()
    parts = regions.subregions(g)
    r = regions.region_table(parts).count()
    assert r == regions.euler_region_count(g).first()["r"]
    assert regions.label_by_faces(g).count() == r - 1
    touched = parts.join(part, [*LABEL, "n"]).select("region_id").distinct().count()
    assert touched >= r - 1
    area = parts.agg(F.sum(F.expr("n * (x1 - x0) * (y1 - y0)"))).first()[0]
    assert area == g.agg(F.sum(F.expr("n * (xh - xl) * (yh - yl)"))).first()[0]
    kept = stateful.label_changed_stateful(g).select(*LABEL, "n", "rnn")
    plain = sweep.label_changed_sets(g).select(*LABEL, "n", "rnn")
    assert kept.exceptAll(plain).isEmpty() and plain.exceptAll(kept).isEmpty()
    strips = sweep.label_changed(g, strips=3)
    assert strips.groupBy("n").count().exceptAll(part.groupBy("n").count()).isEmpty()


@pytest.mark.parametrize("metric", ["linf", "l1"])
def test_sets_by_definition(spark, metric):
    c, f = sample(spark, 4)
    rng = random.Random(9)
    q = spark.createDataFrame([(i, rng.randrange(-5, 70), rng.randrange(-5, 70)) for i in range(60)], "qid long, x long, y long")
    k = circles.nn_circles(c, f, metric)
    by_circle = circles.rnn_of_points(k, metrics.turned(q) if metric == "l1" else q)
    assert by_circle.exceptAll(circles.rnn_by_definition(c, k, q, metric)).isEmpty()
    lattice = circles.nn_circles(c, f, metric, strategy="lattice").select("oid", "r", "nn_fid")
    assert lattice.exceptAll(k.select("oid", "r", "nn_fid")).isEmpty()
    owned = {r["fid"]: r["rnn"] for r in circles.rnn_of_facilities(c, f, k, metric).collect()}
    assert sorted({o for v in owned.values() for o in v}) == [r[0] for r in c.select("oid").orderBy("oid").collect()]


def test_monochromatic(spark):
    p = spark.createDataFrame([(1, 0, 0, 1, "0"), (2, 4, 0, 1, "0"), (3, 10, 0, 1, "0"), (4, 10, 3, 1, "0"), (5, 50, 50, 1, "0"), (6, 50, 50, 1, "0")], points.CLIENTS)
    k = circles.nn_circles_mono(p)
    assert {r["oid"]: r["r"] for r in k.collect()} == {1: 4, 2: 4, 3: 3, 4: 3, 5: 0, 6: 0}
    r = regions.cost_measures(circles.canonical(k)).first()
    assert (r["m"], r["k_all"], r["k"], r["r"], r["lambda_max"]) == (25, 11, 9, 10, 3)


def test_influence_calls(spark, moving):
    labels = sweep.label_changed_sets(moving)
    heat = influence.by_function(labels, len)
    assert sorted(r["heat"] for r in heat.collect()) == sorted(float(r["n"]) for r in labels.collect())
    assert heat.count() == 11
    grouped = influence.by_group_function(sweep.incidence(labels), ["x0", "y0"], len)
    assert sorted(r["heat"] for r in grouped.collect()) == sorted(float(r["n"]) for r in labels.collect() if r["n"])


def disc_table(spark, clients, facilities):
    c = spark.createDataFrame([(*r, 1, "0") for r in clients], points.CLIENTS)
    f = spark.createDataFrame([(*r, 1) for r in facilities], points.FACILITIES)
    return arcs.discs(circles.nn_circles(c, f, "l2"), f)


def test_two_discs(spark):
    d = disc_table(spark, [(1, 0, 0), (2, 6, 0)], [(1, 3, 4)])
    assert arcs.arc_region_count(d).first()["r"] == 4 and arcs.label_arcs(d).count() == 4
    assert arcs.arc_events(d, arcs.arc_vertices(d)).count() == 7
    assert arcs.arc_events(d, arcs.arc_vertices(d), False).count() == 5


def test_concurrent_discs(spark):
    d = disc_table(spark, [(1, 3, 4), (2, -3, 4), (3, 4, -3)], [(1, 0, 0)])
    r = arcs.arc_region_count(d).first()
    assert (r["v"], r["r"], r["k_expected"]) == (4, 7, 8)
    assert arcs.label_arcs(d).count() == 8 and arcs.label_arcs(d, False, False).count() == 26


def test_arc_maximum(spark):
    rng = random.Random(3)
    d = disc_table(spark, [(i, rng.randrange(20_000), rng.randrange(20_000)) for i in range(14)], [(i, rng.randrange(20_000), rng.randrange(20_000)) for i in range(3)]).persist()
    best = arcs.label_arcs(d).agg(F.max("n")).first()[0]
    assert arcs.label_arcs(d, centre_events=False).count() == arcs.label_arcs(d).count() == arcs.arc_region_count(d).first()["k_expected"]
    direct, slabs = arcs.vertex_labels(d), arcs.label_arcs(d)
    count = lambda rows: sorted(r[0] for r in rows.select("n").collect())
    assert count(direct) == count(slabs)
    status = arcs.arc_status(d, arcs.arc_events(d, arcs.arc_vertices(d)), arcs.arc_vertices(d))
    told = arcs.order_mismatches(status).first()
    assert told["mismatches"] == 0 and told["arcs"] == status.count()
    assert status.filter("ys > ym + 1e-9 or ym > yl + 1e-9").isEmpty()
    assert prune.max_region_pruned(d)["max_heat"] == best == prune.max_region_pruned(d, prune=False)["max_heat"]


def test_surface(spark, four):
    labels = sweep.label_all_pairs(four)
    q = spark.createDataFrame([(1, 50, 45), (2, 0, 0), (3, 20, 45)], "qid long, x long, y long")
    assert {r["qid"]: r["heat"] for r in surface.heat_at(labels, q).collect()} == {1: 3, 2: 0, 3: 3}
    pixels = surface.raster(labels, (-13, 110, -11, 85), 12, 9)
    assert pixels.count() == 108 and pixels.agg(F.max("heat")).first()[0] == 3
    assert [r["heat"] for r in surface.top_labels(labels, 2).collect()] == [3, 3]
    assert surface.zoom(labels, (0, 10, 0, 10)).agg(F.max("x1")).first()[0] <= 10


def test_grid_refuses_and_overlay_rejects(four):
    with pytest.raises(grid.OverBudget):
        grid.label_side_grid(four, cells=10)
    with pytest.raises(ValueError):
        grid.superimpose(four, additive=False)


def test_no_facilities(spark):
    c, f = sample(spark, 5)
    with pytest.raises(ValueError):
        circles.nn_circles(c, f.limit(0), "linf")


def test_planner_and_sinks(spark, four, tmp_path):
    plan = planner.choose(four, additive=True)
    assert plan["algorithm"] == "changed_interval" and plan["mode"] == "delta" and plan["m"] == 49
    labels = sweep.label_changed(four).withColumn("heat", F.col("n"))
    points.write_labels(labels, str(tmp_path / "labels"))
    assert spark.read.parquet(str(tmp_path / "labels")).count() == 11
    assert points.polygons(labels, "l1").count() == 11
    metrics.register_sql(spark)
    assert spark.sql("select linf_dist(0, 0, 3, 4), l1_dist(0, 0, 3, 4), l2_dist2(0, 0, 3, 4)").first()[:] == (4, 7, 25)


def test_point_files(spark, tmp_path):
    path = str(tmp_path / "c.csv")
    spark.createDataFrame([(1, 2, 3, 1, "a"), (None, 2, 3, 1, "b")], points.CLIENTS).write.csv(path)
    read = points.read_points(spark, path, "clients", "csv")
    with pytest.raises(Exception, match="null id"):
        read.collect()


@pytest.mark.parametrize("seed", [3, 4])
def test_event_points_of_concurrent_discs(spark, seed):
    """Few facilities on a coarse lattice: many discs through one point, ends and beginnings on others' borders."""
    rng = random.Random(seed)
    d = disc_table(spark, [(i, rng.randrange(12) * 4, rng.randrange(12) * 3) for i in range(24)], [(1, 20, 15), (2, 36, 3)]).persist()
    count = lambda rows: sorted(r[0] for r in rows.select("n").collect())
    assert count(arcs.vertex_labels(d)) == count(arcs.label_arcs(d))


def test_crowded_cells(spark):
    """Nearly all facilities in one spot, clients near and far; a coarse look-up would meet all of them."""
    rng = random.Random(8)
    f = [(i, 5000 + rng.randrange(40), 5000 + rng.randrange(40)) for i in range(300)] + [(900 + i, rng.randrange(20000), rng.randrange(20000)) for i in range(3)]
    c = [(i, rng.randrange(-500, 21000), rng.randrange(-500, 21000), 1, "0") for i in range(120)] + [(500 + i, 5000 + i, 5003, 1, "0") for i in range(30)]
    clients, facilities = spark.createDataFrame(c, points.CLIENTS), spark.createDataFrame([(*r, 1) for r in f], points.FACILITIES)
    for metric, far in (("linf", lambda dx, dy: max(dx, dy)), ("l1", lambda dx, dy: dx + dy), ("l2", lambda dx, dy: dx * dx + dy * dy)):
        want = {r[0]: min((far(abs(r[1] - p[1]), abs(r[2] - p[2])), p[0]) for p in f) for r in c}
        for strategy in ("broadcast", "lattice"):
            got = {r["oid"]: (r["r"], r["nn_fid"]) for r in circles.nn_circles(clients, facilities, metric, strategy).collect()}
            assert got == want


def test_raster_and_grid_by_corners(spark):
    c, f = sample(spark, 6)
    g = circles.canonical(circles.nn_circles(c, f, "linf")).persist()
    box = (-10, 70, -10, 75)
    by_labels, by_corners = surface.raster(sweep.label_all_pairs(g), box, 16, 9), surface.raster_boxes(g, box, 16, 9)
    assert by_labels.exceptAll(by_corners).isEmpty() and by_corners.exceptAll(by_labels).isEmpty()
    rows, squares_of = grid.regular_grid(g, box, 8).collect(), g.collect()
    for r in rows:
        a0, a1, b0, b1 = -10 + r["gx"] * 10, r["gx"] * 10, -10 + r["gy"] * 85 / 8, -10 + (r["gy"] + 1) * 85 / 8
        met = [s for s in squares_of if s["xl"] < a1 and s["xh"] > a0 and s["yl"] < b1 and s["yh"] > b0]
        assert r["crossing"] == sum(not (s["xl"] <= a0 and s["xh"] >= a1 and s["yl"] <= b0 and s["yh"] >= b1) for s in met)
    surface.register_rect_pixels(spark)
    held = spark.sql("select count(*) from rect_pixels(3, 11, 0, 5, 0, 0, 16, 8)").first()[0]
    assert held == sum(3 <= (2 * p + 1) < 11 and 0 <= (2 * q + 1) < 5 for p in range(8) for q in range(8))


def test_full_slab_count(spark):
    from catchment.plans import workloads

    c, f = sample(spark, 7, 40, 4)
    g = circles.canonical(circles.nn_circles(c, f, "linf")).withColumn("tile", F.lit(0)).persist()
    told = workloads.full_slab_count(g, sweep.event_borders(g)).first()["k_all"]
    assert told == sweep.label_all_pairs(g.drop("tile")).count()


def test_far_and_mixed_sizes(spark):
    """Squares of very different sizes, crowded small ones beside large ones that cover or cut them."""
    rng = random.Random(11)
    rows = [(i, x, x + (s := rng.choice([1, 2, 3, 40, 700])), y, y + s) for i in range(60) for x, y in [(rng.randrange(-50, 800), rng.randrange(-50, 60))]]
    g = squares(spark, rows).persist()
    full, part = sweep.label_all_pairs(g).select(*LABEL, "n"), sweep.label_changed(g).select(*LABEL, "n")
    spans = sweep.changed_intervals(g).select("x", "lo", "hi").collect()
    want = [tuple(r) for r in full.collect() if any(x == r["x0"] and lo <= r["y0"] and r["y1"] <= hi for x, lo, hi in spans)]
    assert sorted(map(tuple, part.collect())) == sorted(want)


def test_gadget_source(spark):
    from catchment.sources import gadget_source

    gadget_source.register(spark)
    for kind, make in (("diagonal", gadgets.diagonal_squares), ("disjoint", gadgets.disjoint_squares)):
        read = spark.read.format("gadget").option("kind", kind).option("n", 9).load()
        want = make(spark, 9)
        assert read.drop("oid").exceptAll(want.drop("oid")).isEmpty() and read.count() == 9


def test_near_edges(spark):
    c, _ = sample(spark, 12)
    rows = c.collect()
    got = {tuple(r) for r in influence.near_edges(c, "x", 5).collect()}
    assert got == {(a["oid"], b["oid"]) for a in rows for b in rows if a["oid"] < b["oid"] and a["grp"] == b["grp"] and abs(a["x"] - b["x"]) <= 5}


def test_face_baseline_by_definition(spark):
    c, f = sample(spark, 13)
    g = circles.canonical(circles.nn_circles(c, f, "linf")).persist()
    rows = g.collect()
    for r in regions.label_by_faces(g).collect():
        assert r["n"] == sum(s["n"] for s in rows if 2 * s["xl"] < r["qx"] < 2 * s["xh"] and 2 * s["yl"] < r["qy"] < 2 * s["yh"])


def test_points_are_not_broadcast_by_the_size_of_their_table(spark):
    """Rows that are dealt to cells outgrow their tables, whose size a plan goes by."""
    boxes = spark.range(64).select(F.col("id").alias("oid"), F.col("id").alias("xl"), (F.col("id") * 2 + 1).alias("xh"), F.lit(0).cast("long").alias("yl"), F.lit(9).cast("long").alias("yh"))
    at = spark.range(32).select(F.col("id").alias("qid"), F.col("id").alias("x"), (F.col("id") % 9).alias("y"))
    met = circles.stabbed(at, boxes, "x", "y")
    assert "Broadcast" not in met._jdf.queryExecution().sparkPlan().toString()
    assert met.count() == sum(o <= q <= 2 * o + 1 for q in range(32) for o in range(64))


def test_definition_takes_any_number_of_queries(spark):
    c = spark.range(40).select(F.col("id").alias("oid"), (F.col("id") * 7 % 31).alias("x"), (F.col("id") * 5 % 29).alias("y"), F.lit(1).cast("long").alias("weight"), F.lit("0").alias("grp"))
    f = spark.createDataFrame([(1, 3, 4, 1), (2, 20, 20, 1)], points.FACILITIES)
    q = spark.range(90).select(F.col("id").alias("qid"), (F.col("id") % 30).alias("x"), (F.col("id") % 30).alias("y"))
    k = circles.nn_circles(c, f, "linf")
    few, all_at_once = circles.rnn_by_definition(c, k, q, "linf", most=7), circles.rnn_by_definition(c, k, q, "linf")
    assert few.count() == 90 and few.exceptAll(all_at_once).isEmpty()
    assert few.exceptAll(circles.rnn_of_points(k, q)).isEmpty()


def test_heat_at_points_from_boxes(spark, four):
    at = spark.createDataFrame([(i, i % 13 * 9 - 10, i % 11 * 9 - 11) for i in range(143)] + [(200, 46, 39), (201, 46, 39), (202, 110, 0)], "qid long, x long, y long")
    found = surface.heat_at_boxes(four, at)
    assert found.exceptAll(surface.heat_at(sweep.label_all_pairs(four), at)).isEmpty() and found.count() == at.count()


def crowded(spark, seed=3, n=120, span=60):
    """Squares with ties, touching sides and corners, nested and far-off ones."""
    rng = random.Random(seed)
    rows = [(i, x - r, x + r, y - r, y + r) for i in range(n) for x, y, r in [(rng.randrange(span), rng.randrange(span), rng.randrange(1, 9))]]
    rows += [(1000, -30, 90, -30, 90), (1001, 200, 210, 0, 10), (1002, 210, 220, 10, 20), (1003, 202, 208, 2, 8), (1004, 203, 204, 4, 5)]
    return planner.prepared(squares(spark, rows))


@pytest.mark.parametrize("events", [6, 1024])
def test_counts_by_heat_without_labels(spark, events):
    s = crowded(spark)
    by = lambda rows, column="n": {r[0]: r[1] for r in rows.groupBy(column).count().collect()}
    found = {r["heat"]: r for r in strips.heat_counts(s, events).collect()}
    assert {h: r["k_all"] for h, r in found.items() if r["k_all"]} == by(sweep.label_all_pairs(s))
    assert {h: r["k"] for h, r in found.items() if r["k"]} == by(sweep.label_changed(s))


def test_regions_by_heat_without_regions(spark):
    """The regions of each heat, made one by one or counted; the plan of the count has no label in it."""
    s = crowded(spark)
    table = regions.region_table(regions.subregions(s))
    want = {r[0]: r[1] for r in table.groupBy("n").count().collect()}
    assert {r["heat"]: r["r"] for r in regions.counts_by_heat(s).collect() if r["r"]} == want
    assert regions.region_count(s).first()["r"] == table.count() == regions.euler_region_count(s).first()["r"]
    sums = table.agg(F.sum("n"), F.max("n"), F.avg("n")).first()
    costs = regions.cost_measures(s).first()
    assert (costs["sum_rnn"], costs["lambda_max"], costs["lambda_mean"]) == tuple(sums)


def test_set_diff_is_a_difference_of_counts(spark):
    s = crowded(spark)
    keys = ["x0", "x1", "y0", "y1", "n"]
    saved = sweep.label_all_pairs(s).select(keys).exceptAll(sweep.label_changed(s).select(keys)).groupBy("n").count()
    found = strips.heat_counts(s, 10).filter("k_all > k").select("heat", F.col("k_all") - F.col("k"))
    assert {tuple(r) for r in found.collect()} == {tuple(r) for r in saved.collect()}


@pytest.mark.parametrize("events", [6, 1024])
def test_status_and_pairs_leave_their_strip_without_a_shuffle(spark, events):
    s = crowded(spark)
    each = sweep.line_status(s).groupBy("slab").agg(F.count("*").alias("elements"), F.min("y").alias("lowest"), F.max("y").alias("highest"), F.sum(F.col("pos") * F.when(F.col("role") == "lower", 1).otherwise(-1)).alias("signed_pos"))
    found = strips.status_summary(s, events).join(sweep.event_queue(s).select("slab", F.col("x0").alias("x")), "x").drop("x")
    assert {tuple(r) for r in found.select(each.columns).collect()} == {tuple(r) for r in each.collect()}
    every = sweep.label_all_pairs(s, ("n", "weight")).drop("tile", "slab")
    made = strips.surface_pairs(s, ("n", "weight"), events=events)
    assert sorted(map(tuple, made.collect())) == sorted(map(tuple, every.collect()))
    plan = made._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("RepartitionByExpression") == 1 and not any(w in plan for w in ("Join", "Aggregate", "Window"))
    for box in ((5, 31, 7, 44), (-100, 300, -100, 300), (204, 206, 1, 3), (230, 240, 0, 9)):
        zoomed = strips.surface_pairs(s, box=box, events=events)
        assert sorted(map(tuple, zoomed.collect())) == sorted(map(tuple, surface.zoom(every, box).drop("weight").collect()))


@pytest.mark.parametrize("events", [6, 1024])
def test_sets_of_all_slabs_leave_their_strip_as_runs(spark, events):
    """Equal boxes as one, ties and nested squares; a run is a row until the slabs are listed, and no label meets a join."""
    rows = [(r["oid"], r["xl"], r["xh"], r["yl"], r["yh"]) for r in crowded(spark).collect()]
    s = planner.prepared(squares(spark, rows + [(2000 + i, *r[1:]) for i, r in enumerate(rows[::7])] + [(-1, *rows[0][1:])]))
    keys = ["x0", "x1", "y0", "y1"]
    runs = strips.surface_set_runs(s, events)
    found = strips.slabs_of(runs).select(*keys, "rnn")
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("RepartitionByExpression") == 1 and not any(w in plan for w in ("Join", "Aggregate", "Window"))
    want = sweep.label_all_sets(s).select(*keys, "rnn").collect()
    order = lambda rows: sorted((r["x0"], r["y0"], r["x1"], r["y1"], r["rnn"]) for r in rows)
    assert order(found.collect()) == order(want)
    assert runs.count() < len(want)
    assert strips.surface_set_runs(s.limit(0), events).count() == 0


@pytest.mark.parametrize("events", [6, 40, 1024])
def test_faces_without_slab_rectangles(spark, events):
    """The same points and heats as from the regions of all slab rectangles; none of these is made."""
    s = crowded(spark)
    table = regions.region_table(regions.subregions(s)).filter("at is not null")
    want = {((r["at"]["x0"] + r["at"]["x1"]), (r["at"]["y0"] + r["at"]["y1"]), r["n"]) for r in table.collect()}
    found = regions.label_by_faces(s, events).collect()
    assert len(found) == len(want) and {(r["qx"], r["qy"], r["n"]) for r in found} == want
    assert len({r["region_id"] for r in found}) == len(found)
    if events == 1024:
        assert strips.face_parts(s, events).count() == len(want)
    assert regions.label_by_faces(s.limit(0), events).count() == 0
