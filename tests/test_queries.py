import pytest

from tallywalk.plans.queries import ORACLES, QUERIES
from tests import oracle


@pytest.fixture(scope="module")
def con(sf):
    return oracle.duck(sf)


@pytest.mark.parametrize("name", list(QUERIES))
def test_query(spark, sf, con, name):
    if name in ORACLES:
        assert oracle.differences(spark, con, QUERIES[name], ORACLES[name], sf) == ""
    else:
        assert QUERIES[name](spark, sf).count() > 0


def test_entry(spark):
    import __spark_entry__

    rows = __spark_entry__.entry(spark).collect()
    assert len(rows) == 100 and rows[0]["estimate"] >= rows[-1]["estimate"]
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


MOVED = ["bounds_gated", "bounds_plain", "scenario_one_other_ties", "scenario_one_reported", "scenario_one_true", "scenario_two_first", "scenario_two_second", "sizing_overlap", "sizing_table2", "sizing_table3", "tight_cycle_gated", "tight_cycle_offset"]


@pytest.mark.parametrize("name", MOVED)
def test_a_given_table_is_read(spark, sf, name):
    plan = QUERIES[name](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "parquet" in plan and any(f" {t}" in ORACLES[name] for t in ("lineitem", "events"))


def test_rows_in_turn_whatever_the_keys(spark):
    from tallywalk.plans.queries import in_turn

    keys = [5, 3, 70_000, 2, 10**9, 200_001, 65_536]
    got = in_turn(spark.createDataFrame([(k,) for k in keys], "event_id bigint"), "event_id", 4).collect()
    assert {r["k"]: r["l"] for r in got} == {k: i % 4 for i, k in enumerate(sorted(keys))}
