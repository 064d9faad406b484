"""Worked examples and drawn ranks cover all rows of given tables."""

import pytest

from oracle import connect
from skewjoin import queries
from skewjoin.plans.workloads import intro, micro, repeated
from skewjoin.operators.dispatch import observe

ROUTES = ("micro_routes_four_route", "micro_routes_mirrored", "micro_routes_grid", "intro_routes_stay_replicate", "intro_routes_scatter_replicate")


@pytest.mark.parametrize("name", [*ROUTES, "udtf_zipf"])
def test_scans_a_given_table(spark, small, name):
    files = {f.rsplit("/", 1)[-1] for f in queries.QUERIES[name](spark, small).inputFiles()}
    assert files >= ({"customer.parquet"} if name == "udtf_zipf" else {"lineitem.parquet", "orders.parquet"})


def test_every_customer_has_a_rank(spark, small):
    n = connect(small).execute("SELECT count(*) FROM customer").fetchone()[0]
    assert sum(r["n"] for r in queries.QUERIES["udtf_zipf"](spark, small).collect()) == n


@pytest.mark.parametrize("rows,p", [(micro(), 0.2), (micro(True), 0.2), (intro(), 0.5)])
def test_repeated_examples_keep_their_classes(spark, small, rows, p):
    w = repeated(rows, 3, p)
    x = w.sides(spark, small)
    c = connect(small)
    assert [x.r.count(), x.s.count()] == [c.execute(f"SELECT count(*) FROM {t}").fetchone()[0] for t in ("lineitem", "orders")]
    one = {k: [sum(key == k for key, _ in side) for side in rows] for k in {key for side in rows for key, _ in side}}
    heavy = {k for k, v in one.items() if any(v[i] >= p * len(rows[i]) for i in (0, 1))}
    assert {h.key for h in observe(x, p, 3)[0]} == heavy


@pytest.mark.parametrize("name", ["cost_micro", "cost_micro_printed"])
def test_costs_of_the_examples_grow_with_the_tables(spark, small, name):
    assert max(r["moved"] for r in queries.QUERIES[name](spark, small).collect()) > 100  # 30 rows of an example move fewer
