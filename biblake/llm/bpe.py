"""BPE by backtracking over longest token matches, and decoding by an offset table.

The vocabulary file names merges in order, so a token's rank is the time of its merge. A greedy pass takes the longest
token at each place (from an Aho-Corasick automaton over all tokens); a neighbour pair is allowed only if the merges alone
would not have joined across the border. On a conflict the pass falls back to the next shorter token, or drops the last one
and marks the place as dead. Each place is left at most once, so the work is linear in the word, and the result is that of
applying all merges in order.
"""

from __future__ import annotations

import hashlib
import json
import re
import unicodedata
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biblake.llm.base import Recent, batch, over_batches, slices

TOKENIZER = "word_bpe_49k.json"
#: Words and chunks of more letters (links, encoded data) are worked out each time: the memo is bounded in bytes, not only in entries.
LONG = 64
PRINTABLE = re.compile("[!-~]*").fullmatch
SEPARATORS = re.compile("[\x1c-\x1f]")


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte: itself where it is printable, else the next free one from U+0100."""
    plain = {*range(ord("!"), ord("~") + 1), *range(0xA1, 0xAC + 1), *range(0xAE, 0xFF + 1)}
    free = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(free)) for b in range(256)]


class Tokens:
    """Tables made from a tokenizer file: automaton, next shorter token, pair merges, splits, and the offset table for decoding."""

    def __init__(self, path: str, cache: int = 180_000):
        import ahocorasick
        import regex

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        vocab: dict[str, int] = model["vocab"]
        self.end = model.get("end_of_word_suffix") or ""
        merges = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        #: Symbols are letters; the word end is folded into the last letter of a word as one private character each.
        self.letters = byte_letters()
        self.fold = {c + self.end: chr(0xE000 + i) for i, c in enumerate(self.letters)}
        self.rank: dict[str, int] = {}
        self.ids: list[int] = []
        names: list[str] = []

        def folded(token: str) -> str:
            if self.end and token.endswith(self.end) and len(token) > len(self.end):
                body = token[: -len(self.end)]
                return body[:-1] + self.fold[body[-1] + self.end]
            return token

        def add(token: str, place: str) -> int:
            r = self.rank[place] = len(self.ids)
            self.ids.append(vocab[token])
            names.append(token)
            return r

        for c in [*self.letters, *(c + self.end for c in self.letters)] if self.end else self.letters:
            if c in vocab:
                add(c, folded(c))
        self.n_base = len(self.ids)
        self.split: list[tuple[int, int]] = [(i, i) for i in range(self.n_base)]
        self.pairs: dict[tuple[int, int], int] = {}
        for a, b in merges:
            left, right = self.rank[folded(a)], self.rank[folded(b)]
            place = folded(a + b)
            if place not in self.rank:
                add(a + b, place)
                self.split.append((left, right))
            self.pairs[left, right] = self.rank[place]
        places = sorted(self.rank, key=self.rank.get)
        self.size = [len(p) for p in places]
        #: for each token the longest token that is a proper prefix of it, else -1
        self.shorter = [next((self.rank[p[:n]] for n in range(len(p) - 1, 0, -1) if p[:n] in self.rank), -1) for p in places]
        self.automaton = ahocorasick.Automaton()
        for p, r in self.rank.items():
            self.automaton.add_word(p, (len(p), r))
        self.automaton.make_automaton()
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.special_at = regex.compile("|".join(regex.escape(t) for t in sorted(self.special, key=len, reverse=True))) if self.special else None
        self.pieces = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+")
        #: decoding: the text of id i and a space are blob[offset[i] : offset[i + 1]]
        texts = {i: t for t, i in vocab.items()} | {i: t for t, i in self.special.items()}
        raw = [texts.get(i, "").encode() + b" " for i in range(max(texts) + 1)]
        self.blob = np.frombuffer(b"".join(raw), np.uint8)
        self.offset = np.concatenate([[0], np.cumsum([len(x) for x in raw])])
        self.names = [str(i) for i in self.ids]
        self.words, self.chunks = Recent(self._word, cache, LONG), Recent(self._chunk, cache, LONG)
        self.allowed = Recent(self._allowed, cache)

    def _spine(self, token: int, side: int) -> list[tuple[int, int]]:
        """The tokens that lie at one end of a token (0: its start, 1: its end) as it is made, from itself inwards, each with the rank of the
        merge that takes it up."""
        out, until = [], len(self.ids)
        while True:
            out.append((token, until))
            if token < self.n_base:
                return out
            token, until = self.split[token][side], token

    def _allowed(self, pair: tuple[int, int]) -> bool:
        """Whether two tokens can stand side by side: no merge over the border comes before both its ends are taken up by their own sides.

        Of merges of one rank the leftmost is done first, so one that takes up the right end at the same time comes too late.
        """
        left, right = self._spine(pair[0], 1), self._spine(pair[1], 0)
        over = ((self.pairs.get((x, y)), u, v) for x, u in left for y, v in right)
        return not any(z is not None and z < u and z <= v for z, u, v in over)

    def _longest(self, word: str) -> list[int]:
        """For each place the rank of the longest token that starts there, -1 for none."""
        size, best = [0] * len(word), [-1] * len(word)
        for last, (n, r) in self.automaton.iter(word):
            start = last - n + 1
            if n > size[start]:
                size[start], best[start] = n, r
        return best

    def ranks(self, word: str) -> list[int]:
        best, n = self._longest(word), len(word)
        whole = best[0] if n else -1
        if n and self.size[whole] == n and whole >= 0:
            return [whole]
        dead, out, at = [False] * (n + 1), [], 0
        token = best[0]
        while at < n:
            if token < 0:
                if not out:
                    raise ValueError("a letter is not in the vocabulary")
                dead[at] = True
                token = out.pop()
                at -= self.size[token]
                token = self.shorter[token]
                continue
            to = at + self.size[token]
            if not dead[to] and (not out or self.allowed[out[-1], token]):
                out.append(token)
                at = to
                token = best[at] if at < n else -1
            else:
                token = self.shorter[token]
        return out

    def _word(self, word: str) -> str:
        body = word if PRINTABLE(word) else "".join([self.letters[b] for b in word.encode()])
        if self.end:
            body = body[:-1] + self.fold[body[-1] + self.end]
        return " ".join([self.names[r] for r in self.ranks(body)])

    def _chunk(self, chunk: str) -> str:
        if chunk.isalpha():
            return self.words[chunk]
        if chunk[:-1].isalpha() and chunk[-1] in ".,;:!?":
            return f"{self.words[chunk[:-1]]} {self.words[chunk[-1]]}"
        return " ".join([self.words[w] for w in self.pieces.findall(chunk)])

    def _plain(self, text: str) -> list[str]:
        """Ids of a text without special tokens; no piece crosses white space, so each chunk between is encoded once and kept."""
        if not text.isascii():
            text = unicodedata.normalize("NFC", text).replace("Σ", "σ")  # lowered letter by letter: a last sigma is like any other
        text = text.lower()
        if SEPARATORS.search(text):  # these part chunks for str.split, but not for the tokenizer
            return [self.words[w] for w in self.pieces.findall(text)]
        return list(map(self.chunks.__getitem__, text.split()))

    def encode(self, text: str | None) -> tuple[str, int]:
        """All ids as decimal numbers joined by a space, and their number."""
        text = text or ""
        out: list[str] = []
        at = 0
        for m in self.special_at.finditer(text) if self.special_at and "<|" in text else ():
            out += self._plain(text[at : m.start()])
            out.append(str(self.special[m[0]]))
            at = m.end()
        out += self._plain(text[at:] if at else text)
        ids = " ".join(out)
        return ids, ids.count(" ") + 1 if ids else 0

    def decode(self, ids: np.ndarray) -> bytes:
        """The tokens' texts in UTF-8, joined by a space (the file names no decoder): ranges of the blob, found by offset."""
        if not len(ids):
            return b""
        start, size = self.offset[ids], self.offset[ids + 1] - self.offset[ids]
        ends = np.cumsum(size)
        return self.blob[np.repeat(start - ends + size, size) + np.arange(ends[-1])].tobytes()[:-1]


@lru_cache(2)
def tokens(path: str) -> Tokens:
    return Tokens(path)


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(TOKENIZER)


_OUT = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())])


def encode_documents(documents: DataFrame, path: str | None = None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, ids): the token ids of every row's whole text as array<int>. One pass, no exchange.

    ``path`` names the tokenizer file on every executor. A null or empty text has no ids; rows that repeat repeat; an empty table gives none.
    """
    path = path or default_path()
    kind = documents.schema[key].dataType.simpleString()

    def work(batches):
        t = tokens(path)
        for b in slices(batches):
            ids = [np.array(t.encode(x)[0].split(), np.int32) for x in b.column(1).to_pylist()]
            out = pa.schema([("key", b.schema.field(0).type), ("ids", pa.list_(pa.int32()))])
            yield batch(out, [b.column(0), ids])

    return over_batches(documents.select(key, text), work, f"key {kind}, ids array<int>").withColumnRenamed("key", key)


def digest(documents: DataFrame, path: str | None = None) -> DataFrame:
    """The query's row for each document: what is encoded is decoded again and both are hashed."""
    path = path or default_path()

    def work(batches):
        t = tokens(path)
        for b in slices(batches):
            rows = []
            for doc, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                ids, n = t.encode(text)
                decoded = t.decode(np.array(ids.split(), np.int64))
                rows.append((doc, n, hashlib.sha256(ids.encode()).hexdigest(), hashlib.sha256(decoded).hexdigest()))
            yield batch(_OUT, list(zip(*rows)))

    return over_batches(documents.select(F.col("doc_id").cast("bigint"), "text"), work, "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string")
