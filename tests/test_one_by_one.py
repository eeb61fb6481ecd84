"""Jobs of a sweep follow each other, and the driver lets go of each one's plans."""

from fdrepair import workloads


def test_jobs_follow_each_other(spark, monkeypatch):
    said = []
    monkeypatch.setattr(workloads, "freed", lambda s: said.append("freed"))
    out = workloads.one_by_one(spark, lambda k: said.append(k) or spark.range(k), [1, 2])
    assert said == [1, "freed", 2, "freed"] and sorted(r.id for r in out.collect()) == [0, 0, 1]


def test_the_driver_gives_native_memory_back(spark, monkeypatch):
    """Between algorithms the memory that the driver's compiler and buffers have freed goes back to the system; the heap's collection leaves it with the process."""
    from fdrepair.operators import store

    assert store.trimmed(spark)
    seen = []
    monkeypatch.setattr(store, "trimmed", seen.append)
    store.freed(spark)
    assert seen == [spark]
