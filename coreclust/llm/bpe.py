"""Token counts by rank-synchronous merging of byte pairs.

A text is cut into pre-tokens by the vocabulary's pattern.  Pre-tokens not met before in the
task are laid out as one ragged array of symbol ids.  In every round each sequence applies its
own lowest-ranked pair, at all its places at once, until no sequence has a pair left; what
survives are the tokens.  Counts of short pre-tokens are remembered, up to a bound.

Edge cases.  Null text counts as empty: 0 bytes, 0 tokens.  A special token's string inside a
text is one token, as the library does by default.  Texts of any length are read whole; a
pre-token of any length takes part in the same rounds.
"""

from __future__ import annotations

import functools
import json
import re

import numpy as np
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import encode, map_rows, tokenizer_path

#: Pre-token counts that a task remembers before it starts anew.
REMEMBERED = 400_000
NEVER = np.iinfo(np.int32).max
#: Scripts whose character classes have long been settled; other texts are cut by the library itself.
SETTLED = re.compile("[^\x00-ɏ‐-‧]")
PATTERN = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+")


def byte_alphabet() -> list[str]:
    """The printable character that stands for each byte in the vocabulary file: itself, or the next unused one from U+0100."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in shown]
    return [chr(b) if b in shown else chr(256 + rest.index(b)) for b in range(256)]


class Vocabulary:
    """Merge table of a byte-level vocabulary file: sorted pair keys, their ranks and results."""

    def __init__(self, path: str):
        spec = json.load(open(path, encoding="utf-8"))
        ids = spec["model"]["vocab"]
        pairs = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in spec["model"]["merges"]]
        self.path = path
        self.specials = sorted((t["content"] for t in spec.get("added_tokens", [])), key=len, reverse=True)
        self.special_ids = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        self.split = re.compile("|".join(map(re.escape, self.specials))) if self.specials else None
        self.alphabet = byte_alphabet()
        self.ids = ids
        self.first = np.array([ids[c] for c in self.alphabet], np.int64)
        keys = np.array([ids[a] << 20 | ids[b] for a, b in pairs], np.int64)
        order = np.argsort(keys, kind="stable")
        self.keys, self.ranks = keys[order], order.astype(np.int32)
        self.merged = np.array([ids[a + b] for a, b in pairs], np.int64)
        self._library = None

    def library(self):
        if self._library is None:
            from tokenizers import Tokenizer

            self._library = Tokenizer.from_file(self.path)
        return self._library

    def token_bytes(self) -> dict[bytes, int]:
        back = {c: b for b, c in enumerate(self.alphabet)}
        return {bytes(back[c] for c in t): i for t, i in self.ids.items() if t not in self.special_ids}

    def pretokens(self, text: str) -> tuple[list[str], int]:
        """The pre-tokens, and the number of special tokens between them."""
        parts = self.split.split(text) if self.split else [text]
        out: list[str] = []
        for p in parts:
            if SETTLED.search(p):
                out += [p[a:b] for _, (a, b) in self.library().pre_tokenizer.pre_tokenize_str(p)]
            else:
                out += PATTERN.findall(p)
        return out, len(parts) - 1

    def pair_ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        key = left << 20 | right
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where(self.keys[at] == key, self.ranks[at], NEVER)

    def survivors(self, words: list[bytes]) -> np.ndarray:
        """Symbols left of each byte string when no pair can be merged any more."""
        lengths = np.fromiter(map(len, words), np.int64, len(words))
        counts = lengths.copy()
        live = np.flatnonzero(lengths > 1)
        if not len(live):
            return counts
        sym = self.first[np.frombuffer(b"".join(w for w in words if len(w) > 1), np.uint8)]
        size = lengths[live]
        rank = np.full(len(sym), NEVER, np.int32)
        rank[:-1] = self.pair_ranks(sym[:-1], sym[1:])
        rank[np.cumsum(size) - 1] = NEVER
        while len(live):
            starts = np.cumsum(size) - size
            best = np.minimum.reduceat(rank, starts)
            going = best != NEVER
            if not going.all():
                counts[live[~going]] = size[~going]
                keep = np.repeat(going, size)
                sym, rank, live, size, best = sym[keep], rank[keep], live[going], size[going], best[going]
                if not len(live):
                    break
            at = np.flatnonzero(rank == np.repeat(best, size))
            run = np.concatenate(([True], np.diff(at) != 1))  # places in a row share a symbol: every second one merges
            at = at[(np.arange(len(at)) - np.flatnonzero(run)[np.cumsum(run) - 1]) % 2 == 0]
            sym[at] = self.merged[rank[at]]
            owner = np.searchsorted(np.cumsum(size), at, side="right")
            last = np.zeros(len(sym), bool)
            last[np.cumsum(size) - 1] = True
            ends = last[at + 1]
            keep = np.ones(len(sym), bool)
            keep[at + 1] = False
            last[at[ends]] = True
            now = np.cumsum(keep) - 1
            at, sym, rank, last = now[at], sym[keep], rank[keep], last[keep]
            size = size - np.bincount(owner, minlength=len(size))
            fresh = np.unique(np.concatenate((at, at[at > 0] - 1)))
            nxt = np.minimum(fresh + 1, len(sym) - 1)
            rank[fresh] = np.where(last[fresh], NEVER, self.pair_ranks(sym[fresh], sym[nxt]))
        return counts


@functools.lru_cache(maxsize=2)
def vocabulary_of(path: str) -> Vocabulary:
    """One vocabulary per worker process, whatever the number of its tasks."""
    return Vocabulary(path)


def counts_of(vocabulary: Vocabulary, known: dict[str, int], texts: list[str | None]) -> list[int]:
    cut = [vocabulary.pretokens(t or "") for t in texts]
    new = set().union(*(c for c, _ in cut)) - known.keys()
    if len(known) > REMEMBERED:
        known.clear()
        new = set().union(*(c for c, _ in cut))
    order = list(new)
    known.update(zip(order, vocabulary.survivors([encode(w) for w in order]).tolist(), strict=True))
    out = [sum(map(known.__getitem__, c)) + s for c, s in cut]
    for w in order:
        if len(w) > 64:
            del known[w]
    return out


def count_tokens(docs: DataFrame, vocabulary: str = "byte_bpe_50k.json", limit: int = 1024, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) of every document."""

    def make():
        v, known = vocabulary_of(tokenizer_path(vocabulary)), {}

        def f(ids, texts):
            n = counts_of(v, known, texts)
            return {"doc_id": ids, "n_bytes": [len(encode(t)) for t in texts], "n_tokens": n, "over_limit": [x > limit for x in n]}

        return f

    return map_rows(docs.select(F.col(id_col).alias("doc_id"), F.col(text).alias("text")), make, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
