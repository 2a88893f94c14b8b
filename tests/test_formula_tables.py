"""Formulas are evaluated on sets of the given tables, read by Spark's tasks."""

import duckdb
import pytest
from checks import SMALL

from setstream.plans import catalog


@pytest.mark.parametrize("name", ["band_curve", "bins_guarantee_rows", "cost_table", "fault_bound_rows", "fault_probability", "minwise_check"])
def test_formulas_read_a_table(spark, name):
    df = catalog.QUERIES[name](spark, SMALL)
    assert "parquet" in df._jdf.queryExecution().optimizedPlan().toString().lower() and df.count() > 0


def test_observed_faults_are_near_their_bound(spark):
    rows = catalog.QUERIES["fault_probability"](spark, SMALL).collect()
    assert all(r["observed"] <= r["bound"] + 5 * (r["bound"] / r["slots"]) ** 0.5 + 0.02 for r in rows)


def test_minwise_rates_are_near_ideal(spark):
    rows = {r["family"]: r for r in catalog.QUERIES["minwise_check"](spark, SMALL).collect()}
    assert all(abs(r["observed"] - r["ideal"]) < 0.02 for r in rows.values())


def test_guarantees_stand_on_every_line_of_the_table(spark, duck):
    rows = catalog.QUERIES["bins_guarantee_rows"](spark, SMALL).collect()
    (suppliers,) = duck.execute("SELECT count(DISTINCT l_suppkey) FROM lineitem").fetchone()
    shares = dict(duck.execute("SELECT l_suppkey, count(DISTINCT l_partkey) / (SELECT count(DISTINCT l_partkey) FROM lineitem)::DOUBLE FROM lineitem GROUP BY 1").fetchall())
    assert len(rows) == suppliers * len(catalog.GUARANTEES) and {r["set_id"]: r["r1"] for r in rows} == shares


def test_guarantees_of_small_sets_equal_the_sql_to_the_bit(spark, tmp_path):
    """Sets of 1 to 200 out of 2,000 parts, and lines without a part or a supplier."""
    con = duckdb.connect()
    con.execute("""CREATE TABLE lineitem AS SELECT s AS l_suppkey, (s * 10 + p) % 2000 AS l_partkey, 'N' AS l_returnflag FROM range(1, 201) a(s), range(200) b(p) WHERE p < s
UNION ALL SELECT NULL, p, 'R' FROM range(2000) c(p) UNION ALL SELECT s, NULL, 'R' FROM range(1, 301) d(s)""")
    con.execute(f"COPY lineitem TO '{tmp_path}/lineitem.parquet' (FORMAT parquet)")
    theirs = con.execute(catalog.ORACLES["bins_guarantee_rows"]).fetchall()
    names = [c[0] for c in con.description]
    ours = [tuple(r[c] for c in names) for r in catalog.QUERIES["bins_guarantee_rows"](spark, str(tmp_path)).collect()]
    assert len(ours) == 200 * len(catalog.GUARANTEES) and sorted(ours) == sorted(theirs)
