"""The training-data operators against brute force, exact round trips, libraries and held-out accuracy; and odd inputs."""

import math
import random
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer, models, pre_tokenizers

from taskmesh.llm import context_mixing, encode, minhash, mixing, multi_index, packing, sstable, toxicity, vector_dedup, viterbi
from taskmesh.llm.graph import connected_components
from tests.llm import brute

ODD = [(None, None), (1, ""), (2, None), (3, "  \n\t "), (4, "One"), (5, "one TWO"), (5, "one TWO"), (7, "x" * 20_000), (8, "ab " * 5000), (9, "Ünï cödé | ▁ <|endoftext|> 漢字")]


def corpus(n=240, seed=4, words_each=60):
    rng = random.Random(seed)
    vocabulary = ["".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 6))) for _ in range(400)]
    texts = [[rng.choice(vocabulary) for _ in range(rng.randint(1, words_each))] for _ in range(n // 3)]
    while len(texts) < n:
        copy = list(rng.choice(texts))
        for _ in range(rng.randint(0, 4)):
            copy[rng.randrange(len(copy))] = rng.choice(vocabulary)
        texts.append(copy)
    return {i: " ".join(t) for i, t in enumerate(texts)}


def frame(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string")


def odd(spark):
    return frame(spark, ODD)


def test_components(spark):
    rng = random.Random(1)
    links = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(k, k + 1) for k in range(400, 470)]
    got = {r.node: r.component for r in connected_components(spark.createDataFrame(links, "a long, b long")).collect()}
    want = brute.components(links, {x for p in links for x in p})
    assert got == {k: v for k, v in want.items() if any(k in p and p[0] != p[1] for p in links)}


@pytest.mark.parametrize(("n", "percent"), [(3, 85), (5, 80)])
def test_minhash_finds_the_components_of_all_pairs(spark, n, percent):
    docs = corpus()
    got = {r.doc_id: (r.component_id, r.n_shingles, r.kept) for r in minhash.components(frame(spark, list(docs.items())), minhash.MinHashConfig(n, percent)).collect()}
    want = brute.near_duplicates(docs, n, percent)
    assert {d: c for d, (c, _, _) in got.items()} == want
    assert all(s == len(brute.shingles(docs[d], n)) and k == (c == d) for d, (c, s, k) in got.items())


def test_densified_signatures_estimate_similarity():
    rng = np.random.default_rng(2)
    sequence = minhash.donors(256)
    for size in (40, 2000):
        whole = rng.integers(0, 2**64, size * 2, dtype=np.uint64)
        a, b = np.unique(whole[: size + size // 2]), np.unique(whole[size // 2 :])
        true = len(np.intersect1d(a, b)) / len(np.union1d(a, b))
        same = (minhash.signature(a, 256, sequence) == minhash.signature(b, 256, sequence)).mean()
        assert abs(same - true) < 0.15


def test_minhash_on_odd_rows(spark):
    rows = {(r.doc_id, r.component_id, r.n_shingles, r.kept) for r in minhash.components(odd(spark), minhash.MinHashConfig(3, 85)).collect()}
    assert (None, None, 0, True) in rows and (3, 3, 0, True) in rows and (5, 5, 1, True) in rows and (7, 7, 1, True) in rows
    kept = minhash.drop_near_duplicates(frame(spark, [*ODD, (6, "one two"), (4, "other text")]).withColumn("n.a", F.lit(1)))
    assert kept.columns == ["doc_id", "text", "n.a"]
    ids = sorted(r.doc_id or -1 for r in kept.collect())
    assert ids == [-1, 1, 2, 3, 4, 5, 7, 8, 9]
    assert minhash.components(odd(spark).limit(0), minhash.MinHashConfig()).count() == 0


def test_toxicity_held_out(spark):
    rng = random.Random(3)
    clean = ["".join(rng.choice("klmnop") for _ in range(5)) for _ in range(200)]
    rude = ["vexo", "grubba", "snarl"]
    docs, labels = [], []
    for i in range(1600):
        bad = rng.random() < 0.15
        t = [rng.choice(clean) for _ in range(30)]
        if bad:
            t[rng.randrange(30)] = rng.choice(rude)
        docs.append((i, " ".join(t)))
        if rng.random() < 0.5:
            labels.append((i, int(bad)))
    d, lab = frame(spark, docs), spark.createDataFrame(labels, "doc_id long, toxic int")
    model = toxicity.fit(d, lab)
    out = {r.doc_id: r.score for r in toxicity.score(d, model).collect()}
    bad = {i for i, t in docs if set(t.split()) & set(rude)}
    test = [i for i, _ in docs if brute.held_out(i, 4, 2)]
    right = sum((out[i] >= 0.3) == (i in bad) for i in test)
    assert right >= 0.97 * len(test) and all(0 <= s <= 1 for s in out.values())
    kept = toxicity.filter_toxic(d.withColumn("score", F.lit("own")), lab)
    assert kept.columns == ["doc_id", "text", "score"] and kept.count() == sum(s < 0.3 for s in out.values())
    assert {r.score for r in toxicity.score(odd(spark), toxicity.fit(odd(spark), lab.limit(0))).collect()} == {0.0}


def test_non_negative_risk_does_not_memorise():
    rng = np.random.default_rng(0)
    positive = [np.unique(np.append(rng.integers(10, 3000, 20), 1)) for _ in range(60)]
    unlabelled = [np.unique(rng.integers(10, 3000, 20)) for _ in range(400)]
    model = toxicity.train_nnpu(positive, unlabelled, 0.1)
    assert model.weight[1] > 0 and np.count_nonzero(model.weight[10:3000]) == 0


def test_multi_index_recall_and_order(spark):
    rng = np.random.default_rng(5)
    x = rng.normal(size=(3000, 16)).astype(np.float32)
    rows = [(i, [float(v) for v in x[i]]) for i in range(3000)] + [(5000, None), (5020, [0.0] * 16), (5040, [float("nan")] * 16), (5060, [1.0, 2.0])]
    out = multi_index.search(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), F.col("vec_id") % 20 == 0, k=20, least=1000).collect()
    d = x.astype(float) @ x.astype(float).T
    np.fill_diagonal(d, -np.inf)
    found = {}
    for r in out:
        found.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    assert set(found) == set(range(0, 3000, 20))
    hits = 0
    for q, rs in found.items():
        rs.sort()
        assert [k for k, _, _ in rs] == list(range(1, 21)) and rs == sorted(rs, key=lambda t: (-t[2], t[1]))
        assert all(abs(s - d[q, v]) < 1e-9 for _, v, s in rs)
        hits += len({v for _, v, _ in rs} & set(np.argsort(-d[q])[:20].tolist()))
    assert hits / (20 * len(found)) >= 0.9
    assert multi_index.search(spark.createDataFrame([], "vec_id long, embedding array<double>"), F.col("vec_id") % 20 == 0).count() == 0
    assert multi_index.search(spark.createDataFrame([(0, [1.0]), (1, [2.0])], "vec_id long, embedding array<double>"), F.col("vec_id") % 20 == 0).collect()[0].score == 2.0


def test_heap_walk_passes_cells_in_order():
    rng = np.random.default_rng(6)
    for _ in range(20):
        u, v, counts = rng.normal(size=7), rng.normal(size=5), rng.integers(0, 4, (7, 5))
        wanted = int(rng.integers(1, 30))
        cut = multi_index.walk(u, v, counts, wanted)
        sums = u[:, None] + v[None, :]
        assert counts[sums >= cut].sum() >= min(wanted, counts.sum()) and (counts[sums > cut + 1e-12].sum() < wanted or counts.sum() < wanted)


def test_vector_dedup_equals_all_pairs(spark):
    rng = np.random.default_rng(7)
    base = rng.normal(size=(60, 24))
    x = np.vstack([base, base[:20] + rng.normal(scale=0.06, size=(20, 24)), base[:3].repeat(25, 0) + rng.normal(scale=0.1, size=(75, 24)), base[:5], 2 * base[5:6]])
    rows = [(i, [float(v) for v in r]) for i, r in enumerate(x)] + [(900, None), (901, [0.0] * 24), (902, [float("inf")] * 24), (903, [1.0]), (None, [1.0] * 24)]
    got = {r.vec_id: r for r in vector_dedup.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), block=16).collect()}
    unit = x / np.linalg.norm(x, axis=1)[:, None]
    close = unit @ unit.T >= 0.95
    np.fill_diagonal(close, False)
    comp = brute.components([tuple(p) for p in np.argwhere(close)], range(len(x)))
    for i in range(len(x)):
        assert (got[i].n_links, got[i].component_id, got[i].kept) == (close[i].sum(), comp[i], comp[i] == i)
    assert all(got[i].n_links == 0 and got[i].kept for i in (900, 901, 902, 903, None))
    assert vector_dedup.near_duplicates(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


@pytest.mark.parametrize("spec", [encode.BYTE_BPE, encode.WORD_BPE])
def test_encoder_equals_the_library(spec):
    rng = random.Random(8)
    parts = ["a", "the", "Word", " ", "\n", "'s", "|", "é", "　", "\x85", "\x1c", "漢", "<|endoftext|>", "1", ",", "!?", "İ", "ß", "́", "e"]
    texts = ["".join(rng.choice(parts) for _ in range(rng.randint(0, 16))) for _ in range(4000)]
    library = Tokenizer.from_file(public_tokenizers.path(spec[0]))
    library.encode_special_tokens = True
    want = [e.ids for e in library.encode_batch(texts, add_special_tokens=False)]
    assert [np.frombuffer(i, "<u4").tolist() for i in encode.Encoder(public_tokenizers.path(spec[0]), spec[1]).encode([t.encode() for t in texts])] == want


def test_sstable_round_trip_and_lookup(spark, tmp_path):
    docs = frame(spark, [*ODD, *[(100 + i, f"text number {i}") for i in range(300)], (-7, "negative")])
    shards = sstable.write_shards(docs, f"file://{tmp_path}", docs_per_shard=64)
    assert shards.count() >= 4
    rows = sorted(sstable.read_shards(shards).collect(), key=lambda r: r.start)
    assert [r.doc_id for r in rows[:2]] == [None, -7] and [r.doc_id for r in rows[1:]] == sorted(r.doc_id for r in rows[1:])
    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    library.encode_special_tokens = True
    want = Counter()
    for r in docs.collect():
        ids = np.array([*library.encode(r.text or "", add_special_tokens=False).ids, 0], "<u4")
        want[r.doc_id, len(ids), zlib.crc32(ids.tobytes())] += 1
    assert Counter((r.doc_id, r.n_tokens, r.ids_crc32) for r in rows) == want
    place = 0
    for r in rows:
        assert r.start == place
        place += r.n_tokens
    assert len(sstable.lookup(shards, 5)) == 2 and sstable.lookup(shards, 100)[0].tolist() == [*library.encode("text number 0").ids, 0] and sstable.lookup(shards, 99_999) == []
    assert sstable.read_shards(sstable.write_shards(docs.limit(0), f"file://{tmp_path}/none")).count() == 0


def test_sstable_shards_get_larger_instead_of_more(spark, tmp_path):
    docs = frame(spark, [*ODD, *[(100 + i, f"text number {i}") for i in range(300)]])
    few = sstable.write_shards(docs, f"file://{tmp_path}/few", docs_per_shard=16, most_shards=3)
    many = sstable.write_shards(docs, f"file://{tmp_path}/many", docs_per_shard=16)
    assert few.count() <= 3 < many.count()
    assert sorted(map(repr, sstable.read_shards(few).collect())) == sorted(map(repr, sstable.read_shards(many).collect()))


def test_language_model(spark):
    rng = random.Random(9)
    follow = {w: rng.sample([f"w{k}" for k in range(40)], 3) for w in [f"w{k}" for k in range(40)]}
    docs = []
    for i in range(400):
        w = [f"w{rng.randrange(40)}"]
        while len(w) < 60:
            w.append(rng.choice(follow[w[-1]]))
        docs.append((i, " ".join(w)))
    docs += [(1000 + i, t) for i, (_, t) in enumerate(ODD)]
    out = {r.doc_id: r for r in context_mixing.score_documents(frame(spark, docs)).collect()}
    counts = Counter()
    for i, t in docs:
        if not brute.held_out(i, 7, 2):
            counts.update([*brute.words(t), b""])
    n, v = sum(counts.values()), len(counts)
    for i, t in docs:
        tokens = [*brute.words(t), b""]
        r = out[i]
        assert r.base_score == pytest.approx(sum(math.log10((counts[w] + 1) / (n + v + 1)) for w in tokens), abs=1e-6)
        assert (r.n_tokens, r.n_known, r.train_tokens, r.held_out) == (len(tokens), sum(counts[w] > 0 for w in tokens), n, brute.held_out(i, 7, 2)) and r.score < 0
    held = [out[i] for i in range(400) if out[i].held_out]
    assert sum(r.score for r in held) > 0.75 * sum(r.base_score for r in held)  # words follow words: far better than counts
    assert context_mixing.score_documents(frame(spark, docs).limit(0)).count() == 0


def test_code_is_a_probability():
    code = context_mixing.make_code([(b"a", 5), (b"b", 3), (b"", 2)], np.zeros(context_mixing.ENDINGS, int), np.ones(context_mixing.CLASSES))
    assert sum(0.5**d for d in np.diff(code.starts)) == pytest.approx(1.0)


def test_packing(spark):
    docs = frame(spark, [*ODD, *[(200 + i, "token " * (37 * i % 900)) for i in range(120)]])
    rows = packing.pack_documents(docs, capacity=512, with_ids=True).collect()
    library = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    library.encode_special_tokens = True
    want = Counter()
    for r in docs.collect():
        ids = np.array([*library.encode(r.text or "", add_special_tokens=False).ids, 1], "<u4")
        for k in range(0, len(ids), 512):
            want[r.doc_id, k // 512, k, len(ids[k : k + 512]), zlib.crc32(ids[k : k + 512].tobytes())] += 1
    assert Counter((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in rows) == want
    places = {}
    for r in rows:
        places.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for own in places.values():
        at = 0
        for offset, length in sorted(own):
            assert offset == at
            at += length
        assert at <= 512
    assert len(places) <= math.ceil(sum(r.length for r in rows) / 512) + 2
    joined = packing.sequences(spark.createDataFrame(rows)).collect()
    assert sum(len(r.ids) for r in joined) == 4 * sum(r.length for r in rows)
    assert packing.pack_documents(docs.limit(0)).count() == 0


def test_best_two_fit_replaces_the_smallest():
    counts = np.zeros(11, int)
    counts[[6, 3, 2]] = 1, 1, 2  # greedy: 6 + 3, gap 1; two twos fill the place of the three
    assert packing.best_two_fit(counts)[0] == ((6, 2, 2), 1)


def test_token_counts_equal_the_library(spark):
    rng = random.Random(10)
    for vocabulary in (viterbi.zipf_unigram(), [("<unk>", 0.0), *[(p, float(-rng.randint(1, 3))) for p in ["▁", "a", "b", "ab", "ba", "aba", "▁a", "▁ab", "bb", "c"]]]):
        library = Tokenizer(models.Unigram(vocabulary, 0))
        library.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.Metaspace(prepend_scheme="always")])
        counter = viterbi.Counter(vocabulary)
        for _ in range(3000):
            text = "".join(rng.choice(["a", "b", "the", "c", "d", " ", "\n", "▁", "漢", "\x1c", "<unk>", "İ"]) for _ in range(rng.randint(0, 14)))
            assert counter.text(text)[0] == len(library.encode(text, add_special_tokens=False).ids)
    out = viterbi.count_tokens(odd(spark).withColumn("n_tokens", F.lit("own")), viterbi.zipf_unigram(), "pieces")
    assert out.columns == ["doc_id", "text", "n_tokens", "pieces", "pieces_unknown"] and out.where("text IS NULL").first().pieces == 0


def test_mixing_targets_and_copies(spark):
    rng = random.Random(11)
    docs = [(i, "w " * rng.randint(0, 60), rng.choice(["a", "b", "c", "d", None])) for i in range(2000)] + [(5000, "x " * 3, "tiny"), (5001, None, "empty")]
    df = spark.createDataFrame(docs, "doc_id long, text string, source string").withColumn("extra.x", F.lit(1))
    sized = mixing.sizes(df)
    plan = mixing.with_copies(sized, mixing.rates(sized)).collect()
    size = Counter()
    for _, t, s in docs:
        size[s] += len((t or "").split())
    order = sorted((s for s in size if s is not None), key=lambda s: s.encode()) + [None]
    weight = {s: 1 + k % 3 for k, s in enumerate(order)}
    target, full = {}, set()
    while True:
        left = sum(size.values()) - sum(3 * size[s] for s in full)
        share = {s: left * weight[s] / sum(weight[x] for x in order if x not in full) for s in order if s not in full}
        over = {s for s in share if share[s] > 3 * size[s]}
        if not over:
            target = share | {s: 3 * size[s] for s in full}
            break
        full |= over
    taken = Counter()
    for r in plan:
        assert r.target == pytest.approx(target[r.source]) and r.source_size == size[r.source] and 0 <= r.copies <= 3
        taken[r.source] += r.size * r.copies
    assert all(abs(taken[s] - target[s]) <= 0.02 * max(200, target[s]) for s in order)
    mixed = mixing.mix(df)
    assert mixed.columns == df.columns and Counter(r.doc_id for r in mixed.collect()) == Counter({r.doc_id: r.copies for r in plan if r.copies})
    assert mixing.mix(df.limit(0)).count() == 0
