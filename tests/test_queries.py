import compare
import pytest

import __spark_entry__
from stagedrel.plans import extras, workloads

SF = "/root/testdata/sf0.001"
SQL = workloads.ORACLE_SQL | extras.ORACLE_SQL
ALL = workloads.QUERIES | extras.QUERIES


@pytest.fixture(scope="module")
def con():
    return compare.duck(SF)


@pytest.mark.parametrize("name", sorted(SQL))
def test_query_equals_its_sql(spark, con, name):
    assert compare.differs(ALL[name](spark, SF), con, SQL[name]) is None


def test_entry(spark):
    df = __spark_entry__.entry(spark)
    assert df.count() > 0 and df.columns == ["sample_id", "k", "reward", "objective"]
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def test_late_events_are_dropped(spark):
    late = extras.late_data(spark, SF).first()
    assert late["counted"] < late["events"]


def test_repeated_batches_add_nothing(spark, tmp_path):
    from stagedrel.streaming.rewards import exactly_once_sink

    path = f"file://{tmp_path}/rollouts"
    write = exactly_once_sink(path, ["epoch", "step", "sample_id", "k"])
    batch = spark.createDataFrame([(1, 1, i, k, 0.5) for i in range(3) for k in range(2)], "epoch int, step int, sample_id long, k int, reward double")
    for b in (batch, batch, batch.union(batch)):
        write(b, 0)
    assert spark.read.parquet(path).count() == 6
