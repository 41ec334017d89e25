import os

from gsample.plans.materialize import distill, materialize, shared_dir


def tables(spark):
    at = shared_dir(spark).removeprefix("file://").removeprefix("file:")
    return set(os.listdir(at)) if os.path.isdir(at) else set()


def test_distill_keeps_its_table_alone(spark):
    before, held = tables(spark), materialize(spark.range(5), "held")

    def make():
        nested = distill(spark, lambda: materialize(spark.range(10), "inner").where("id < 8"), "nested")
        return materialize(nested.where("id < 6"), "outer").join(held, "id")

    out = distill(spark, make, "out")
    assert sorted(r["id"] for r in out.collect()) == [0, 1, 2, 3, 4]
    assert held.count() == 5
    assert sorted(t.split("-")[0] for t in tables(spark) - before) == ["held", "out"]


def test_distill_deletes_nothing_written_before_or_after(spark):
    out = distill(spark, lambda: spark.range(3), "plain")
    later = materialize(spark.range(4), "later")
    distill(spark, lambda: materialize(out, "way"), "again")
    assert (out.count(), later.count()) == (3, 4)
