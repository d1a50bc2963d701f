import datetime
import math

import pytest

from veilmatch.operators import cost
from veilmatch.plans import catalog


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("orders"))
    day = lambda k: datetime.date(2024, 1, k)
    rows = [(c, day(1)) for c in range(1, 13)] * 2 + [(7, day(2)), (None, day(2)), (None, day(3)), (3, None)] + [(c, day(4)) for c in range(30)]
    spark.createDataFrame(rows, "o_custkey long, o_orderdate date").repartition(3).write.parquet(f"{path}/orders.parquet")
    return path


def test_costs_of_the_databases_that_orders_give(spark, folder):
    get = lambda name: catalog.QUERIES[name](spark, folder)
    sizes = {1: 12, 2: 1, 4: 30}
    assert {r.db.day: r["size"] for r in catalog.databases(spark, folder).collect()} == sizes
    got = {r.db.day: r for r in get("traffic_formula").collect()}
    assert {k: (r["size"], r.n_bytes, r.published_mb) for k, r in got.items()} == {k: (n, 31208 * n + 28640, {1: 0.34, 2: 0.04, 4: 0.84}[k]) for k, n in sizes.items()}
    assert {r.db.day: (r.levels, r.n_rounds) for r in get("rounds_formula").collect()} == {k: (math.ceil(math.log2(n)), 13 + 5 * math.ceil(math.log2(n))) for k, n in sizes.items()}
    assert {r.db.day: r.a for r in get("published_speedups").collect()} == {1: round(10.92 / 1.88, 2), 2: round(8.47 / 1.28, 2), 4: round(11.39 / 2.09, 2)}
    seconds = {(r.db.day, r.profile): (r.seconds, r.published_seconds) for r in get("modelled_seconds").collect()}
    alone = {(r["size"], r.profile): r.seconds for r in cost.modelled(spark, (1, 12, 30)).collect()}
    assert {k: v[0] for k, v in seconds.items()} == {(k, p): alone[n, p] for k, n in sizes.items() for p in "ABC"} and seconds[1, "B"][1] == 1.91


def test_error_totals_are_those_of_the_registry(spark, sf):
    got = {r.tau_bp: r for r in catalog.QUERIES["published_error_totals"](spark, sf).collect()}
    none = spark.createDataFrame([], "good boolean, two long, three long")
    some = spark.createDataFrame([(True, 9000, 6000), (False, 7001, 7000)], none.schema)
    links = spark.range(5)
    assert {r.total_two for r in cost.measured_totals(none, links).collect()} == {5}
    assert {r.tau_bp: (r.total_two, r.total_three) for r in cost.measured_totals(some, links).collect()} == {6000: (5, 6), 6500: (5, 6), 7000: (5, 5), 7500: (4, 5), 8000: (4, 5), 8500: (4, 5)}
    assert set(got) == {r[0] for r in cost.ERRORS} and got[6000].published_two == 1150
    assert len({(r.total_two, r.total_three) for r in got.values()}) > 1
    pivot = {r.method: r for r in catalog.QUERIES["ops_pivot_methods"](spark, sf).collect()}
    assert pivot["total_two"].at_7000 == got[7000].total_two and pivot["total_three"].at_8000 == got[8000].total_three


@pytest.mark.parametrize("name", ["traffic_formula", "rounds_formula", "modelled_seconds", "published_speedups"])
def test_a_given_table_is_read(spark, sf, name):
    assert any("orders.parquet" in f for f in catalog.QUERIES[name](spark, sf).inputFiles())
