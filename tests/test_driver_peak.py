"""The driver's memory stays low while a table is written and after a model is learned, not only between stored tables."""

import threading

import numpy as np
import pytest

from taskmesh.llm import toxicity
from taskmesh.sources import materialise, storage


def _told(monkeypatch, committed):
    """Collections, where the heap of 1000 is as large as ``committed`` says and shrinks to 300 by each."""
    seen = threading.Event()

    class Heap:
        totalMemory = staticmethod(lambda: committed[0])
        freeMemory = staticmethod(lambda: committed[0] - 100)
        maxMemory = staticmethod(lambda: 1000)

    class Spark:
        class sparkContext:
            applicationId = "of-this-test"

        class _jvm:
            class java:
                class lang:
                    class Runtime:
                        getRuntime = staticmethod(lambda: Heap)

                    class System:
                        @staticmethod
                        def gc():
                            committed[0] = committed[1]
                            seen.set()

    monkeypatch.setattr(storage, "_settled", {})
    return Spark, seen


def test_a_heap_that_is_large_but_hardly_used_shrinks(monkeypatch):
    spark, seen = _told(monkeypatch, [900, 300])
    assert storage.relieve(spark) and seen.is_set()
    assert not storage.relieve(spark)


def test_a_heap_full_of_live_data_is_collected_once(monkeypatch):
    spark, _ = _told(monkeypatch, [900, 800])
    assert storage.relieve(spark) and not storage.relieve(spark)


def test_the_heap_is_looked_at_while_a_job_runs(monkeypatch):
    spark, seen = _told(monkeypatch, [900, 300])
    monkeypatch.setattr(storage, "WATCH_S", 0.01)
    with storage.watched(spark):
        assert seen.wait(20)


def test_a_failing_job_ends_the_watch(spark, monkeypatch):
    before = threading.active_count()
    with pytest.raises(Exception, match="no such thing"):
        materialise(spark.range(3).selectExpr("raise_error('no such thing') AS x"), "failing")
    assert "taskmesh-heap" not in [t.name for t in threading.enumerate()] and threading.active_count() <= before + 1


def test_a_fit_gives_its_memory_back_and_learns_as_before(spark, monkeypatch):
    docs = spark.createDataFrame([(i, f"plain words {i % 7} here" + " vexo" * (i % 3 == 0)) for i in range(300)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 3 == 0)) for i in range(300)], "doc_id long, toxic int")
    seen, train = [], toxicity.train_nnpu

    def learn(positive, unlabelled, *args, **named):
        for sets in (positive, unlabelled):
            assert sets and all(d.dtype == np.int32 for d in sets) and [d.tobytes() for d in sets] == sorted(d.tobytes() for d in sets)
        seen.append("learned")
        return train(positive, unlabelled, *args, **named)

    monkeypatch.setattr(toxicity, "train_nnpu", learn)
    monkeypatch.setattr(toxicity, "release", lambda: seen.append("released"), raising=False)
    toxicity.fit(docs, labels)
    assert seen == ["learned", "released"]
