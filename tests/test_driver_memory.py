"""What is done with does not stay on the driver."""

from taskmesh.sources import materialise, relieve


def _collections(spark):
    beans = spark._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans()
    return sum(b.getCollectionCount() for b in beans)


def test_garbage_is_collected_before_the_heap_is_full(spark):
    assert not relieve(spark, 1.0)
    before = _collections(spark)
    assert relieve(spark, 0.0) and _collections(spark) > before


def test_stored_tables_are_where_it_is_looked_at(spark, monkeypatch):
    seen = []
    monkeypatch.setattr("taskmesh.sources.storage.relieve", lambda s: seen.append(s))
    assert materialise(spark.range(3), "three").count() == 3 and seen == [spark]
