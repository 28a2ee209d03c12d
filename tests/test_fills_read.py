"""Fills whose seeds and spacings come from the rows of a table, not from constants or row counts alone."""

import pytest
from pyspark.sql import functions as F

from frontfill import catalog
from frontfill.functions.lattice import CENTRE, RADIUS
from frontfill.sources import tables as T


@pytest.mark.parametrize(("name", "d"), [("q01_fill_disc_seq", 2), ("q03_fill_ball_seq", 3), ("q04_fill_variable_seq", 2), ("q06_fill_annulus_candidates", 2)])
def test_seed_is_a_supplier(spark, name, d):
    sf = "/root/testdata/sf0.01"
    xs = [f"x{a}" for a in range(d)]
    rows = [tuple(r) for r in T.supplier(spark, sf, d).select(*xs).collect()]
    gap = {p: sum((v - CENTRE) ** 2 for v in p) for p in rows}
    first = catalog.queries()[name](spark, sf).where(F.col("seq") == 0).select(*xs).collect()
    assert [tuple(r) for r in first] == [min(gap, key=gap.get)] and min(gap.values()) <= RADIUS**2


def test_queues_start_at_a_supplier(spark, monkeypatch):
    from frontfill.catalog import fills

    asked = []
    start = fills._first_row
    monkeypatch.setattr(fills, "_first_row", lambda *a: asked.append(1) or start(*a))
    assert all(r.violations == 0 and r.open == 0 for r in fills.q01b_queue_orders(spark, "/root/testdata/sf0.001").collect())
    assert len(asked) == 3


@pytest.mark.parametrize(("name", "inside", "area"), [("q05b_fill_box_boundary_seeds", lambda x, y: 1_000_000 <= x <= 13_000_000 and 2_000_000 <= y <= 9_000_000, 12_000_000 * 7_000_000), ("q05c_fill_polygon_boundary_seeds", None, None)])
def test_border_fills_are_sized_by_the_suppliers_inside(spark, name, inside, area):
    from frontfill.catalog import fills
    from frontfill.functions import domain as D

    sf = "/root/testdata/sf0.01"
    rows = T.supplier(spark, sf).select("x0", "x1").collect()
    n = sum(inside(*r) for r in rows) if inside else sum(bool(D.Polygon(fills.KITE).test(tuple(r))) for r in rows)
    got = catalog.queries()[name](spark, sf).select("h_parent").distinct().collect()
    assert [r.h_parent for r in got] == [int((0.8 * (area or fills.KITE_AREA) / n) ** 0.5)]


@pytest.mark.parametrize("name", ["q07_fill_phased", "q07b_fill_phased_distributed"])
def test_phased_fills_are_sized_by_the_customers_inside(spark, small, name):
    from frontfill.functions.lattice import size_h

    rows = T.customer(spark, small).select("x0", "x1").collect()
    n = sum((r.x0 - CENTRE) ** 2 + (r.x1 - CENTRE) ** 2 <= RADIUS**2 for r in rows)
    got = catalog.queries()[name](spark, small).select("h").distinct().collect()
    assert [r.h for r in got] == [size_h(n)]
