"""Near duplicates where rows repeat an id, with the same text or with another."""

from taskmesh.llm import minhash

CONFIG = minhash.MinHashConfig(shingle=3, percent=85)


def found(spark, rows):
    out = minhash.components(spark.createDataFrame(rows, "doc_id long, text string"), CONFIG).collect()
    return sorted((r.doc_id, r.component_id) for r in out)


def text(n=102, head=0, tail=0, mark="y"):
    return " ".join([f"{mark}h{k}" for k in range(head)] + [f"w{k}" for k in range(head, n - tail)] + [f"{mark}t{k}" for k in range(tail)])


def test_link_that_stars_miss_with_a_repeated_row(spark):
    centre, one, other = text(head=11), text(), text(tail=7)  # one and other share 93 of 107; the centre is tried first and fails
    assert found(spark, [(0, centre), (1, one), (2, other)]) == [(0, 0), (1, 1), (2, 1)]
    assert found(spark, [(0, centre), (1, one), (1, one), (2, other)]) == [(0, 0), (1, 1), (1, 1), (2, 1)]


def test_repeated_id_with_another_text(spark):
    far, near = text(head=14, mark="f"), text(tail=1)
    assert found(spark, [(0, near), (1, far), (1, near), (2, text())]) == [(0, 0), (1, 0), (1, 1), (2, 0)]
