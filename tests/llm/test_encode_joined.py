"""New pieces of a text go through the library many at a time, with the ids they have by themselves."""

import random

import numpy as np
import public_tokenizers
from tokenizers import Tokenizer, models, pre_tokenizers

from taskmesh.llm import encode


def texts_of(seed, n=60):
    rng = random.Random(seed)
    letters = "abcdefghijklmnop" + "ABCÄÖüßéñÿ"
    ends = ["", "", "", ",", ".", "...", "?!", ".\nNext", "'s", "&&&", "-2,50", " ", "　x", "漢字", "<|endoftext|>", "\x1c", "Ġ", "Ċ", "\u0085"]
    word = lambda: "".join(rng.choice(letters) for _ in range(rng.randint(1, 9))) + rng.choice(ends)
    texts = [" ".join(word() for _ in range(rng.randint(0, 80))) for _ in range(n)]
    return [*texts, *[" ".join(rng.choice(letters) for _ in range(40)) for _ in range(5)], "one  two", " lead", "trail ", "Ġ Ġa Ġ", "a " * 3000, "x" * 40_000 + " y", "a b  c"]


def test_joined_pieces_have_the_ids_of_the_library():
    path = public_tokenizers.path(encode.BYTE_BPE[0])
    library = Tokenizer.from_file(path)
    library.encode_special_tokens = True
    for entries in (400_000, 20):
        enc = encode.Encoder(path, False, entries)
        for seed in range(4):
            texts = texts_of(seed)
            for text, got in zip(texts, enc.encode([t.encode() for t in texts]), strict=True):
                assert np.frombuffer(got, "<u4").tolist() == library.encode(text, add_special_tokens=False).ids, text


def test_new_words_take_few_calls_of_the_library(monkeypatch):
    enc, calls = encode.Encoder(public_tokenizers.path(encode.BYTE_BPE[0]), False), []
    own = enc.pieces.tokenize
    enc.pieces.tokenize = lambda text: calls.append(text) or own(text)
    enc.whole([""])
    monkeypatch.setattr(enc, "whole", lambda texts, own=enc.whole: calls.extend(texts) or own(texts))
    rng = random.Random(1)
    enc.encode([" ".join("".join(rng.choice("etaoins") for _ in range(8)) + rng.choice(["", ".", "&&&"]) for _ in range(3000)).encode()])
    assert len(calls) < 30


def test_a_vocabulary_that_joins_words_is_asked_piece_by_piece(tmp_path):
    vocabulary = {c: k for k, c in enumerate(["a", "b", "Ġ", "Ġa", "bĠa", "abĠa"])}
    tokenizer = Tokenizer(models.BPE(vocabulary, [("Ġ", "a"), ("b", "Ġa"), ("a", "bĠa")]))
    tokenizer.pre_tokenizer = pre_tokenizers.ByteLevel(add_prefix_space=False)
    tokenizer.save(str(tmp_path / "joins.json"))
    text = "a ab ab a b ab"
    got = encode.Encoder(str(tmp_path / "joins.json"), False).encode([text.encode()])[0]
    assert np.frombuffer(got, "<u4").tolist() == tokenizer.encode(text, add_special_tokens=False).ids
