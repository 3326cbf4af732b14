"""Whole texts to ids of a public tokenizer, through a bounded cache of pieces.

Both vocabularies treat a text piece by piece, and a piece's ids do not depend on its neighbours if the text is cut at the
right places, so pieces are looked up and only new ones go through the tokenizers library:

* byte-level vocabulary: its pattern starts a new piece at a single space between two characters that are not white space.
  Texts in which a space touches other white space, or an end of the text, are encoded whole, by the library itself.
* vocabulary with word ends: white space is dropped, so ASCII white space always separates pieces.

New pieces that are a word of Latin letters, perhaps with punctuation behind it, are one word for both patterns, so they go
straight to the library's model, as its byte alphabet spells them; all others go through the library's whole encoding. For
the byte-level vocabulary a text's new pieces go there many at a time, one after another with a space before each: a space
inside a token would tell that pieces were joined, and every token that begins with one begins a piece.
Strings of special tokens in a text are ordinary text.
"""

from __future__ import annotations

import re
from array import array
from collections.abc import Iterable, Iterator

import numpy as np
import public_tokenizers
from tokenizers import Tokenizer

from taskmesh.llm.words import kept

#: Pieces in each of the two generations of the cache; a full one takes the place of the older. They bound memory only.
CACHE_ENTRIES = 400_000
#: New pieces, and bytes of them, that go through the library at a time.
LEARNED_PIECES, LEARNED_BYTES = 512, 1 << 15

_ASCII_WORD = re.compile(rb"([A-Za-z]+)([.,;:!?]*)")
_WORD = re.compile("([A-Za-zÀ-ÖØ-öø-ÿ]+)([.,;:!?]*)")
#: White space of more than one byte, and the control characters that some count as such.
_LATE_SPACE = {c.encode() for c in "\x85\xa0\u1680\u2028\u2029\u202f\u205f\u3000" + "".join(map(chr, range(0x2000, 0x200B)))}
_SPACE = frozenset(b" \t\n\r\x0b\x0c\x1c\x1d\x1e\x1f")
_PLAIN = [*range(33, 127), *range(161, 173), *range(174, 256)]
#: The byte alphabet of both vocabularies: printable bytes stand for themselves, the others follow from 256 on, in order.
_ALPHABET = {b: b for b in _PLAIN} | {b: 256 + k for k, b in enumerate(b for b in range(256) if b not in _PLAIN)}

_SPACE_SIGN = chr(_ALPHABET[32])


class Pieces(dict):
    """ids of pieces, by the tokenizer's own rules; new ones are encoded as they are asked for. None for a piece that tells a
    text that must be encoded whole. Pieces of the byte-level vocabulary are as they stand after a space."""

    def __init__(self, owner: Encoder, older: dict[bytes, bytes | None]) -> None:
        super().__init__()
        self.owner, self.older, self.tokenize = owner, older, owner.tokenizer.model.tokenize

    def __missing__(self, piece: bytes) -> bytes | None:
        found = self.older.get(piece)
        if found is None:
            if m := _ASCII_WORD.fullmatch(piece):  # letters that the byte alphabet spells as themselves
                word, end = m.groups()
                if end:
                    found = self[word] + self.owner.end(end.decode())
                else:
                    text = piece.decode()
                    found = array("I", [t.id for t in self.tokenize(text.lower() if self.owner.drops_space else f"{_SPACE_SIGN}{text}")]).tobytes()
            elif m := _WORD.fullmatch(text := piece.decode()):
                word, end = m.groups()
                if end:
                    found = self[word.encode()] + self.owner.end(end)
                else:
                    found = self.owner.word(word.lower() if self.owner.drops_space else f" {word}")
            else:
                found = self._other(text)
        self[piece] = found
        return found

    def _other(self, text: str) -> bytes | None:
        if self.owner.drops_space:
            return self.owner.whole([text])[0]
        return None if not text or text[0].isspace() or text[-1].isspace() else self.owner.whole([f" {text}"])[0]


class Encoder:
    """ids of texts, as little-endian unsigned 32-bit bytes."""

    def __init__(self, path: str, drops_space: bool, entries: int = CACHE_ENTRIES) -> None:
        self.entries = entries
        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        self.drops_space = drops_space
        model = self.tokenizer.model
        self.joins = not drops_space and not any(getattr(model, a, None) for a in ("dropout", "ignore_merges", "continuing_subword_prefix", "end_of_word_suffix"))
        if self.joins:
            vocabulary = self.tokenizer.get_vocab()
            self.starts = np.zeros(max(vocabulary.values()) + 1, bool)
            self.starts[[k for token, k in vocabulary.items() if token.startswith(_SPACE_SIGN)]] = True
        self.ends: dict[str, bytes] = {}
        self.pieces = Pieces(self, {})

    def whole(self, texts: list[str]) -> list[bytes]:
        """By the library, without the cache."""
        return [np.array(e.ids, "<u4").tobytes() for e in self.tokenizer.encode_batch(texts, add_special_tokens=False)]

    def word(self, word: str) -> bytes:
        """Letters, perhaps after a space: one word for the patterns."""
        return array("I", [t.id for t in self.pieces.tokenize(word.encode().decode("latin-1").translate(_ALPHABET))]).tobytes()

    def end(self, punctuation: str) -> bytes:
        if punctuation not in self.ends:
            if len(self.ends) > 1000:
                self.ends.clear()
            (self.ends[punctuation],) = self.whole([punctuation])
        return self.ends[punctuation]

    def learn(self, new: Iterable[bytes]) -> None:
        """Takes up pieces that the cache does not hold, many at a time."""
        pieces, older = self.pieces, self.pieces.older
        ascii_words, words, ended, others = {}, {}, [], []
        for piece in new:
            if piece in older:
                pieces[piece] = older[piece]
                continue
            if m := _ASCII_WORD.fullmatch(piece):
                word, end = m.groups()
                if not end or (word not in pieces and word not in older):
                    ascii_words[word] = None
            elif m := _WORD.fullmatch(text := piece.decode()):
                word, end = m.groups()
                word, end = word.encode(), end.encode()
                if not end or (word not in pieces and word not in older):
                    words[word] = None
            else:
                if not text or text[0].isspace() or text[-1].isspace():
                    pieces[piece] = None
                else:
                    others.append(piece)
                continue
            if end:
                ended.append((piece, word, end.decode()))
        model = lambda spelled: [t.id for t in pieces.tokenize(spelled)]
        for part in _parts(ascii_words):
            self._take(part, model((b" " + b" ".join(part)).decode().replace(" ", _SPACE_SIGN)))
        for part in _parts(words):
            self._take(part, model((b" " + b" ".join(part)).decode("latin-1").translate(_ALPHABET)))
        for part in _parts(others):
            self._take(part, self.tokenizer.encode((b" " + b" ".join(part)).decode(), add_special_tokens=False).ids)
        for piece, word, end in ended:
            pieces[piece] = pieces[word] + self.end(end)

    def _take(self, part: list[bytes], ids: list[int]) -> None:
        """ids: of the pieces one after another, each with a space before it."""
        found = np.array(ids, "<u4")
        at = np.flatnonzero(self.starts[found])
        if len(at) != len(part):  # a token spans pieces: one at a time then
            for piece in part:
                self.pieces[piece]
            return
        data, bounds = found.tobytes(), [*(at * 4).tolist(), 4 * len(found)]
        for piece, low, high in zip(part, bounds[:-1], bounds[1:], strict=True):
            self.pieces[piece] = data[low:high]

    def encode(self, texts: list[bytes]) -> list[bytes]:
        """texts: UTF-8. They are split one at a time, since a text's pieces need far more memory than it does."""
        out = []
        for text in texts:
            if len(self.pieces) > self.entries:
                self.pieces.older = {}
                self.pieces = Pieces(self, dict(self.pieces))
            out.append(self._encode(text))
        return out

    def _encode(self, text: bytes) -> bytes:
        if self.drops_space:
            return b"".join(map(self.pieces.__getitem__, text.split()))
        head, *rest = text.split(b" ")
        if rest and (not head or head[-1] in _SPACE or head[-2:] in _LATE_SPACE or head[-3:] in _LATE_SPACE):
            return self.whole([text.decode()])[0]
        if self.joins:
            known = self.pieces
            if new := {p for p in rest if p not in known}:
                self.learn(new)
        try:
            tail = b"".join(map(self.pieces.__getitem__, rest))
        except TypeError:  # a piece is None
            return self.whole([text.decode()])[0]
        return self._head(head.decode()) + tail

    def _head(self, text: str) -> bytes:
        """A text's first piece, which no space precedes."""
        if m := _WORD.fullmatch(text):
            word, end = m.groups()
            return self.word(word) + self.end(end) if end else self.word(word)
        return self.whole([text])[0]


def _parts(pieces: Iterable[bytes]) -> Iterator[list[bytes]]:
    """So many pieces, or bytes of them, at a time; one at least."""
    part, size = [], 0
    for piece in pieces:
        if part and (len(part) >= LEARNED_PIECES or size + len(piece) > LEARNED_BYTES):
            yield part
            part, size = [], 0
        part.append(piece)
        size += len(piece)
    if part:
        yield part


def encoder(name: str, drops_space: bool, entries: int = CACHE_ENTRIES) -> Encoder:
    """name: a file of the public tokenizers, or a path. One for each worker process, kept from task to task while they want the same."""
    return kept((name, drops_space, entries), lambda: Encoder(name if "/" in name else public_tokenizers.path(name), drops_space, entries))


BYTE_BPE = ("byte_bpe_50k.json", False)
WORD_BPE = ("word_bpe_49k.json", True)
