"""Extents from scenario files, synthetic ones, and the bucketed sink."""

import pytest
from py4j.protocol import Py4JJavaError
from pyspark.errors import PySparkException

from tickspace.sources.adapters import save_bucketed, scenario, synthetic

SPANS = {"x": (-50, 50), "y": (0, 7)}


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_synthetic_extent_hangs_on_nothing_but_its_arguments(spark):
    one = synthetic(spark, 500, SPANS, parts=1)
    assert rows(one) == rows(synthetic(spark, 500, SPANS, parts=7))
    assert rows(one) != rows(synthetic(spark, 500, SPANS, seed=8))
    assert {r.y for r in one.collect()} == set(range(7))
    assert all(-50 <= r.x < 50 for r in one.collect())
    assert synthetic(spark, 0, SPANS).count() == 0
    with pytest.raises(ValueError):
        synthetic(spark, 5, {"x": (3, 3)})


@pytest.mark.parametrize("fmt", ["csv", "json"])
def test_scenario_files(spark, tmp_path, fmt):
    agents = synthetic(spark, 40, SPANS)
    agents.write.option("header", True).format(fmt).save(str(tmp_path / fmt))
    back = scenario(spark, str(tmp_path / fmt), ["id", "x", "y"], fmt)
    assert back.schema.simpleString() == "struct<id:bigint,x:bigint,y:bigint>"
    assert rows(back) == rows(agents)


def test_scenario_of_wrong_types_or_names_fails(spark, tmp_path):
    (tmp_path / "a.csv").write_text("id,x\n1,north\n")
    (tmp_path / "b.csv").write_text("id,z\n1,2\n")
    for name in ("a.csv", "b.csv"):
        with pytest.raises((PySparkException, Py4JJavaError)):
            scenario(spark, str(tmp_path / name), ["id", "x"]).collect()
    with pytest.raises(ValueError):
        scenario(spark, str(tmp_path / "a.csv"), ["id"], "xml")


def test_bucketed_extents_join_without_an_exchange(spark, tmp_path):
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        a = save_bucketed(synthetic(spark, 300, SPANS), "extent_a", buckets=4, path=str(tmp_path / "a"))
        b = save_bucketed(synthetic(spark, 200, {"z": (0, 9)}), "extent_b", buckets=4, path=str(tmp_path / "b"))
        both = a.join(b, "id")
        assert "Exchange" not in both._jdf.queryExecution().executedPlan().toString()
        assert both.count() == 200
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
        for name in ("extent_a", "extent_b"):
            spark.sql(f"DROP TABLE IF EXISTS {name}")
