"""Byte-level BPE encoding by backtracking, and decoding by an offset table.

The encoder never replays merges.  An Aho-Corasick automaton over the
vocabulary gives the longest token at each byte; a token is accepted after its
left neighbour only if the pair is compatible, i.e. if merging would have
left both of them standing.  On a conflict the encoder tries the next shorter
token and, if there is none, takes the previous token back.  Positions that
failed once are never tried again, so each byte is visited a bounded number of
times.  The result equals the merge procedure token for token.

Decoding gathers bytes from one flat buffer through an offset table.

Defined results: null text is the empty text; empty text gives no ids and the
digest of the empty string; other columns are ignored; repeated rows are each
encoded.
"""

from __future__ import annotations

import functools
import hashlib
import json
from collections.abc import Iterable
from itertools import chain

import ahocorasick
import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import map_texts, table

# The pre-token classes of byte-level BPE, with Unicode white space spelled out.
_W = "\\t-\\r\\x20\\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"
PRE_TOKEN = rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{_W}\p{{L}}\p{{N}}]+|[{_W}]+(?![^{_W}])|[{_W}]+"
CACHE_WORDS = 400_000


def _byte_alphabet() -> dict[str, int]:
    """Printable stand-in character of each byte in byte-level vocabularies."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    hidden = [b for b in range(256) if b not in set(shown)]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}


class Codec:
    """Encoder and decoder of one vocabulary file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        alphabet = _byte_alphabet()
        model = spec["model"]
        raw = {t: bytes(alphabet[c] for c in t) for t in model["vocab"]}
        size = max([*model["vocab"].values(), *(t["id"] for t in spec["added_tokens"])]) + 1
        pieces = [b""] * size
        for t, i in model["vocab"].items():
            pieces[i] = raw[t]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        for t, i in self.special.items():
            pieces[i] = t.encode()
        self.pieces = pieces
        self.numbers = [str(i) for i in range(size)]
        # Decoding table: piece i is flat[offsets[i]:offsets[i + 1]].
        self.flat = np.frombuffer(b"".join(pieces), dtype=np.uint8)
        self.lengths = np.array([len(p) for p in pieces], dtype=np.int64)
        self.offsets = np.concatenate([[0], np.cumsum(self.lengths)])
        # Merge rank of each pair, and the two halves of each merged token.
        ids = model["vocab"]
        self.rank: dict[tuple[int, int], int] = {}
        self.halves: dict[int, tuple[int, int]] = {}
        self.born: dict[int, int] = {}
        for r, m in enumerate(model["merges"]):
            a, b = m.split(" ") if isinstance(m, str) else m
            pair, whole = (ids[a], ids[b]), ids[a + b]
            self.rank.setdefault(pair, r)
            if whole not in self.born:
                self.born[whole], self.halves[whole] = r, pair
        self.automaton = ahocorasick.Automaton()
        self.shorter = [-1] * size
        known = {p: i for t, i in ids.items() if (p := raw[t])}
        for p, i in known.items():
            self.automaton.add_word(p.decode("latin-1"), (len(p), i))
            self.shorter[i] = next((known[p[:n]] for n in range(len(p) - 1, 0, -1) if p[:n] in known), -1)
        self.automaton.make_automaton()
        self.fits: dict[tuple[int, int], bool] = {}
        self.words: dict[str, tuple[int, ...]] = {}
        self.find = regex.compile(PRE_TOKEN).findall
        self.cut = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")") if self.special else None

    def compatible(self, left: int, right: int) -> bool:
        """True if merging the two tokens' bytes leaves exactly these two tokens.

        The tokens are undone latest merge first; at every stage the pair that
        faces the seam must not merge earlier than what is still undone.
        """
        key = (left, right)
        known = self.fits.get(key)
        if known is not None:
            return known
        a, b, limit, good = left, right, float("inf"), True
        while True:
            seam = self.rank.get((a, b))
            if seam is not None and seam < limit:
                good = False
                break
            ra, rb = self.born.get(a, -1), self.born.get(b, -1)
            if ra < 0 and rb < 0:
                break
            if ra > rb:  # the left token was completed last: the seam met its right half before
                limit, a = ra, self.halves[a][1]
            else:  # at equal ranks the left of two equal merges comes first, hence the + 1
                limit, b = rb + 1, self.halves[b][0]
        if len(self.fits) > 2_000_000:
            self.fits.clear()
        self.fits[key] = good
        return good

    def encode_word(self, word: bytes) -> list[int]:
        """Exact merges of one pre-token."""
        n = len(word)
        longest = [-1] * n
        reach = [0] * n
        for end, (size, token) in self.automaton.iter(word.decode("latin-1")):
            start = end - size + 1
            if size > reach[start]:
                reach[start], longest[start] = size, token
        open_ = bytearray(b"\x01") * (n + 1)
        out: list[int] = []
        pos, token = 0, longest[0]
        lengths, shorter = self.lengths, self.shorter
        while pos < n:
            while token >= 0:
                end = pos + int(lengths[token])
                if open_[end] and (not out or self.compatible(out[-1], token)):
                    break
                token = shorter[token]
            if token >= 0:
                out.append(token)
                pos = end
                token = longest[pos] if pos < n else -1
            else:  # nothing fits here: this position is closed, retry the one before
                open_[pos] = 0
                token = out.pop()
                pos -= int(lengths[token])
        return out

    def _word(self, word: str) -> tuple[int, ...]:
        found = self.words.get(word)
        if found is None:
            if len(self.words) >= CACHE_WORDS:
                self.words.clear()
            found = self.words[word] = tuple(self.encode_word(word.encode("utf-8", "surrogatepass")))
        return found

    def encode(self, text: str) -> list[int]:
        if self.cut is not None and any(s in text for s in self.special):
            out: list[int] = []
            for part in self.cut.split(text):
                out += [self.special[part]] if part in self.special else chain.from_iterable(map(self._word, self.find(part)))
            return out
        return list(chain.from_iterable(map(self._word, self.find(text))))

    def decode(self, ids: Iterable[int]) -> str:
        i = np.asarray(ids, dtype=np.int64)
        if not len(i):
            return ""
        sizes = self.lengths[i]
        ends = np.cumsum(sizes)
        places = np.arange(ends[-1]) + np.repeat(self.offsets[i] - (ends - sizes), sizes)
        return self.flat[places].tobytes().decode("utf-8", "replace")


@functools.lru_cache(maxsize=2)
def codec(path: str) -> Codec:
    return Codec(path)


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def encode_documents(docs: DataFrame, vocabulary: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, ids array<int>) of every row."""
    path = vocabulary or default_vocabulary()

    def start():
        c = codec(path)
        return lambda texts: {"ids": [c.encode(t) for t in texts]}

    return map_texts(docs, start, "ids array<int>", id_col, text_col)


def decode_documents(encoded: DataFrame, vocabulary: str | None = None, id_col: str = "doc_id") -> DataFrame:
    """(id, text) from (id, ids); null ids decode to the empty text."""
    path = vocabulary or default_vocabulary()

    @F.pandas_udf("string")
    def text(ids: pd.Series) -> pd.Series:
        c = codec(path)
        return ids.map(lambda i: "" if i is None else c.decode(i))

    return encoded.select(id_col, text("ids").alias("text"))


def encoded_digests(docs: DataFrame, vocabulary: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Number of tokens and digests of ids and of the decoded text; ids never leave the worker."""
    path = vocabulary or default_vocabulary()

    def start():
        c, sha = codec(path), hashlib.sha256

        def work(texts):
            out = {"n_tokens": [], "ids_sha256": [], "decoded_sha256": []}
            for t in texts:
                ids = c.encode(t)
                out["n_tokens"].append(len(ids))
                out["ids_sha256"].append(sha(",".join(map(c.numbers.__getitem__, ids)).encode()).hexdigest())
                out["decoded_sha256"].append(sha(c.decode(ids).encode()).hexdigest())
            return out

        return work

    return map_texts(docs, start, "n_tokens long, ids_sha256 string, decoded_sha256 string", id_col, text_col)


def op2_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encoded_digests(table(spark, sf_dir, "documents").select("doc_id", "text"))
