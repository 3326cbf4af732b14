"""The registered queries themselves, on the smallest tables, against plain versions."""

import hashlib
import math
import re
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from taskmesh.llm import multi_index, registry, toxicity
from tests.llm import brute

SF = "/root/testdata/sf0.001"
KINDS = ("email", "ip", "card", "phone")


@pytest.fixture(scope="module")
def docs(spark):
    return {r.doc_id: r for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}


@pytest.fixture(scope="module")
def rows(spark):
    return {name: query(spark, SF).collect() for name, query in registry.queries().items()}


def library(name):
    out = Tokenizer.from_file(public_tokenizers.path(name))
    out.encode_special_tokens = True
    return out


def luhn(digits):
    return sum(sum(divmod(2 * int(c), 10)) if k % 2 else int(c) for k, c in enumerate(reversed(digits))) % 10 == 0


def plain_spans(text):
    """The base kinds by their patterns as they are stated."""
    digits = lambda m: re.sub("[^0-9]", "", m.group())
    keep = {
        "email": (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda m: True),
        "ip": (r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda m: all(int(p) <= 255 for p in m.group().split("."))),
        "card": (r"[0-9]([\x20-]?[0-9])+", lambda m: 13 <= len(digits(m)) <= 19 and luhn(digits(m))),
        "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: 9 <= len(digits(m)) <= 15),
    }
    return [(kind, *m.span()) for kind in KINDS for m in re.finditer(keep[kind][0], text) if keep[kind][1](m)]


def test_every_document_has_its_row(rows, docs, spark):
    vectors = spark.read.parquet(f"{SF}/embeddings.parquet").count()
    for name in ("op1_minhash", "op2_toxicity", "op4_sstable", "op5_context_mixing", "op8_viterbi", "op9_mixing", "op10_pii"):
        assert sorted(r.doc_id for r in rows[name]) == sorted(docs), name
    assert len(rows["op7_vector_dedup"]) == vectors


def test_minhash(rows, docs):
    want = brute.near_duplicates({d: r.text for d, r in docs.items()}, 3, 85)
    assert {r.doc_id: r.component_id for r in rows["op1_minhash"]} == want


def test_personal_data(rows, docs):
    for r in rows["op10_pii"]:
        base = plain_spans(docs[r.doc_id].text or "")
        count = Counter(k for k, _, _ in base)
        assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == tuple(count[k] for k in KINDS)
        joined = ",".join(f"{k}:{s}:{e}" for k, s, e in base)
        assert r.base_sha256 == hashlib.sha256(joined.encode()).hexdigest() and r.spans.startswith(joined)


def test_token_files(rows, docs):
    enc, start = library("byte_bpe_50k.json"), 0
    for r in sorted(rows["op4_sstable"], key=lambda r: r.doc_id):
        ids = np.array([*enc.encode(docs[r.doc_id].text or "", add_special_tokens=False).ids, 0], "<u4")
        assert (r.start, r.n_tokens, r.ids_crc32) == (start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)


def test_packing(rows, docs):
    enc, want = library("word_bpe_49k.json"), Counter()
    for d, r in docs.items():
        ids = np.array([*enc.encode(r.text or "", add_special_tokens=False).ids, 1], "<u4")
        for k in range(0, len(ids), 4096):
            want[d, k // 4096, k, len(ids[k : k + 4096]), zlib.crc32(ids[k : k + 4096].tobytes())] += 1
    assert Counter((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in rows["op6_packing"]) == want
    bins = {}
    for r in rows["op6_packing"]:
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert all(sorted(b)[0][0] == 0 and all(x[0] + x[1] == y[0] for x, y in zip(sorted(b), sorted(b)[1:], strict=False)) and sum(n for _, n in b) <= 4096 for b in bins.values())
    assert len(bins) <= math.ceil(sum(r.length for r in rows["op6_packing"]) / 4096) + 1


def test_language_model_base(rows, docs):
    train = Counter()
    tokens = {d: [*brute.words(r.text), b""] for d, r in docs.items()}
    for d, t in tokens.items():
        if not brute.held_out(d, 7, 2):
            train.update(t)
    n, v = sum(train.values()), len(train)
    for r in rows["op5_context_mixing"]:
        t = tokens[r.doc_id]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (brute.held_out(r.doc_id, 7, 2), len(t), sum(train[w] > 0 for w in t), n)
        assert r.base_score == pytest.approx(sum(math.log10((train[w] + 1) / (n + v + 1)) for w in t), rel=1e-9) and r.score < 0


def test_neighbours(spark, rows):
    vectors = spark.read.parquet(f"{SF}/embeddings.parquet").collect()
    ids, x = np.array([r.vec_id for r in vectors]), np.array([r.embedding for r in vectors], float)
    place, hits = {v: k for k, v in enumerate(ids.tolist())}, 0
    found = {}
    for r in rows["op3_multi_index"]:
        found.setdefault(r.query_id, []).append(r)
        assert r.score == pytest.approx(float(x[place[r.query_id]] @ x[place[r.vec_id]]), abs=1e-12)
    assert set(found) == {v for v in ids.tolist() if v % 20 == 0} and all(len(rs) == 20 for rs in found.values())
    for q, rs in found.items():
        s = x @ x[place[q]]
        s[place[q]] = -np.inf
        hits += len({r.vec_id for r in rs} & set(ids[np.lexsort((ids, -s))[:20]].tolist()))
    assert hits >= 0.9 * 20 * len(found)


def test_an_id_that_occurs_twice_asks_once(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(60, 8))
    table = [(i, [float(v) for v in x[i]]) for i in range(60)] + [(20, [float(v) for v in x[20]])]
    out = multi_index.search(spark.createDataFrame(table, "vec_id long, embedding array<double>"), multi_index.F.col("vec_id") % 20 == 0).where("query_id = 20").collect()
    want = sorted(((-float(x[20] @ x[i]), i) for i in range(60) if i != 20))[:20]
    assert [r.vec_id for r in sorted(out, key=lambda r: r["rank"])] == [i for _, i in want]


def test_toxicity_scores_by_hand(spark, docs, rows):
    """The query's scores are those of its model, worked out word by word; labels of the held-out fold change nothing."""
    d, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    held = [r.doc_id for r in labels.collect() if brute.held_out(r.doc_id, 4, 2)]
    turned = labels.withColumn("toxic", toxicity.F.when(toxicity.F.col("doc_id").isin(held), 1 - toxicity.F.col("toxic")).otherwise(toxicity.F.col("toxic")))
    model, other = toxicity.fit(d, labels), toxicity.fit(d, turned)
    assert np.array_equal(model.weight, other.weight) and model.bias == other.bias
    for r in rows["op2_toxicity"]:
        buckets = set().union(*[toxicity.features(w) for w in brute.words(docs[r.doc_id].text)])
        evidence = sum(model.weight[b] for b in buckets)
        want = 1 / (1 + math.exp(-evidence - model.bias)) if model.weight.any() else 0.0
        assert r.score == pytest.approx(want, abs=1e-9) and r.predicted == int(r.score >= 0.3) and r.held_out == brute.held_out(r.doc_id, 4, 2)
