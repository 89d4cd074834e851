"""Grid, CSR, predicates: frozen counts, edge boxes, algebra."""

import pytest
from pyspark.sql import functions as F

from recall_engine.functions import kdop, polygons
from recall_engine.operators import csr, grid
from recall_engine.sources.layers import layer, octagon, ring, workload

FROZEN = {"w1": (727, 380), "w2": (1395, 10), "w3": (692, 210), "w4": (4694, 1454)}


@pytest.mark.parametrize("w", FROZEN)
def test_frozen_counts(spark, sf, w):
    pairs = grid.candidates(*workload(spark, sf, w))
    assert (pairs.count(), pairs.where(kdop.relate("covers")).count()) == FROZEN[w]


def boxes(spark, rows):
    return octagon(spark.createDataFrame(rows, "id string, x0 long, x1 long, y0 long, y1 long"))


EDGE = [("a", 0, 10, 0, 10), ("b", 10, 20, 0, 10), ("c", 10, 20, 10, 20), ("p", 10, 10, 10, 10), ("n", -30, -10, -30, -10), ("m", -10, 0, -10, 0), ("big", -100, 100, -100, 100), ("far", 500, 510, 500, 510)]


@pytest.mark.parametrize("theta", [(5.0, 5.0), (10.0, 10.0), (17.3, 3.1), (200.0, 200.0)])
def test_every_way_equals_nested_loop(spark, theta):
    s = boxes(spark, EDGE)
    expected = {(r.s_id, r.t_id) for r in grid.nested_loop(s, s).collect()}
    ways = {
        "refpoint": grid.candidates(s, s, theta), "distinct": grid.candidates(s, s, theta, "distinct"),
        "band": grid.band_join(s, s, theta[0]), "classes": grid.extent_classes(s, s, theta, 4),
    }
    for name, pairs in ways.items():
        got = [(r.s_id, r.t_id) for r in pairs.select("s_id", "t_id").collect()]
        assert len(got) == len(set(got)) and set(got) == expected, name


def test_empty_side(spark, sf):
    s, t = workload(spark, sf, "w1")
    assert grid.candidates(s.limit(0), t).count() == 0 == grid.candidates(s, t.limit(0)).count()


def test_shared_cells_by_counting(spark, sf):
    s, t = workload(spark, sf, "w1")
    theta = grid.cell_size(s)
    counted = grid.box_hits(grid.cell_pairs(grid.assign_cells(s, theta), grid.assign_cells(t, theta))).groupBy("s_id", "t_id").count()
    both = grid.candidates(s, t, theta).join(counted, ["s_id", "t_id"])
    assert both.where("shared_cells <> count").count() == 0 and both.count() == FROZEN["w1"][0]


def test_csr_round_trip(spark, sf):
    pairs = grid.candidates(*workload(spark, sf, "w4"))
    for limit in (None, 3):
        rows = csr.build(pairs, limit)
        flat = csr.explode(rows)
        assert flat.count() == pairs.count() and flat.select("index").distinct().count() == pairs.count()
        assert flat.agg(F.max("index")).first()[0] == pairs.count() - 1
        assert flat.select("s_id", "t_id").exceptAll(pairs.select("s_id", "t_id")).count() == 0
        assert limit is None or rows.where(F.col("row_len") > limit).count() == 0


def test_predicates_of_octagons(spark):
    rows = [("s", 0, 40, 0, 40), ("in", 15, 25, 15, 25), ("same", 0, 40, 0, 40), ("edge", 40, 80, 0, 40), ("corner", 40, 80, 40, 80), ("gap", 36, 76, 36, 76), ("over", 20, 60, 0, 40), ("out", 100, 120, 0, 20)]
    x = boxes(spark, rows)
    a, b = (x.select(*[F.col(c).alias(f"{k}_{c}") for c in x.columns]) for k in "st")
    both = a.crossJoin(b).withColumns({p: kdop.relate(p) for p in kdop.PREDICATES} | {"s_ring": ring("s_"), "t_ring": ring("t_")})
    got = {(r.s_id, r.t_id): r for r in both.collect()}
    true = lambda i: {p for p in kdop.PREDICATES if got["s", i][p]}
    assert true("in") == {"intersects", "contains", "covers", "overlaps"} - {"overlaps"}
    assert true("same") == {"intersects", "contains", "covers", "within", "covered_by", "equals"}
    assert true("edge") == {"intersects", "touches"} and true("corner") == {"disjoint"} and true("gap") == {"disjoint"}
    assert true("over") == {"intersects", "overlaps"} and true("out") == {"disjoint"}
    for (i, j), r in got.items():
        back = got[j, i]
        assert r["covers"] == back["covered_by"] and r["disjoint"] != r["intersects"] and not (r["touches"] and r["overlaps"])
        m = polygons.matrix(r.s_ring, r.t_ring)
        assert {p: polygons.holds(m, p) for p in kdop.PREDICATES} == {p: r[p] for p in kdop.PREDICATES}, (i, j, m)


def test_general_path_agrees_on_a_workload(spark, sf):
    pairs = grid.candidates(*workload(spark, sf, "w3")).withColumns({p: kdop.relate(p) for p in kdop.PREDICATES} | {"a": ring("s_"), "b": ring("t_")})
    for r in pairs.select("a", "b", *kdop.PREDICATES).collect():
        m = polygons.matrix(r.a, r.b)
        assert all(polygons.holds(m, p) == r[p] for p in kdop.PREDICATES), m


def test_matrix_of_concave_polygons():
    u = [(0, 0), (9, 0), (9, 9), (6, 9), (6, 3), (3, 3), (3, 9), (0, 9)]
    assert polygons.holds(polygons.matrix(u, [(4, 5), (5, 5), (5, 8), (4, 8)]), "disjoint")
    assert polygons.holds(polygons.matrix(u, [(3, 4), (6, 4), (6, 8), (3, 8)]), "touches")
    assert polygons.holds(polygons.matrix(u, [(1, 1), (2, 1), (2, 2), (1, 2)]), "contains")
    assert polygons.holds(polygons.matrix(u, [(2, 5), (7, 5), (7, 6), (2, 6)]), "overlaps")
    assert polygons.matrix(u, [(0, 0), (1, 1)]) is None


def test_simplify_and_projection(spark):
    import math

    circle = [(math.cos(k / 50 * math.pi), math.sin(k / 50 * math.pi)) for k in range(100)]
    got = polygons.simplify([{"x": x, "y": y} for x, y in circle], 0.1)
    assert 4 <= len(got) < 30 and all(math.isclose(math.hypot(*p), 1) for p in got)
    assert len(polygons.simplify([(0, 0), (5, 0.05), (10, 0), (10, 10), (0, 10)], 0.1)) == 4
    x, y = polygons.to_metres(F.lit(180.0), F.lit(90.0))
    r = spark.range(1).select(x.alias("x"), y.alias("y")).first()
    assert abs(r.x - 20037508.342789244) < 1e-6 and abs(r.y - r.x) < 1e-3


def test_well_known_text(spark, sf):
    from recall_engine.sources import io

    x = layer(spark, sf, "s_cust").limit(20).select("id", ring().alias("ring"))
    back = x.withColumn("again", io.from_wkt(io.to_wkt(F.col("ring"))))
    assert back.where("ring <> again").count() == 0


def test_plans_have_no_cartesian_or_python(spark, sf):
    pairs = grid.candidates(*workload(spark, sf, "w4"), theta=(80.0, 80.0)).where(kdop.relate("covers"))
    plan = pairs._jdf.queryExecution().executedPlan().toString()
    assert not any(n in plan for n in ("CartesianProduct", "BroadcastNestedLoopJoin", "Python", "SinglePartition"))
