"""Benchmark decontamination with an FM-index per training shard.

A task gathers documents into shards of a bounded number of words.  Words outside the
benchmark's vocabulary and the ends of documents are separators; the stretches between them
that could hold a window are sorted into a suffix array, whose transform is kept in a wavelet
matrix.  All windows are searched backwards at once, their occurrences are located by walking
to sampled suffix positions, and the occurrences are merged into removal spans.

Distinct benchmark rows are dealt by hash into blocks of about `BLOCK_WORDS` words.  The driver
holds the windows of one block at a time; with several blocks each pass is written before the
next block is read, and the passes' spans are united, so nothing unbounded is broadcast.

Edge cases.  Null or empty text: no words, nothing hit.  Null or empty items have no window.
Items are told apart by their id as text: repeated rows of an item, and several texts of one id,
are one item.  An item without an id has windows, which are hit and removed, but no name, so it
is neither counted nor listed.  An empty benchmark or table gives clean rows or none.  Repeated
documents are answered each.  A document longer than a shard, or an item longer than a block,
is one of its own.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ALNUM_WORDS, Scratch, encode, map_rows, ragged, slices

SHARD_WORDS = 1_000_000
BLOCK_WORDS = 500_000
#: Every so many text positions the suffix array is kept.
SAMPLE = 8


def words_of(text: str | None) -> list[bytes]:
    return encode(text).translate(ALNUM_WORDS).split()


class BitRanks:
    """A bit vector with constant-time counts of ones before a position."""

    def __init__(self, bits: np.ndarray):
        n = len(bits)
        packed = np.packbits(bits.astype(np.uint8), bitorder="little")
        self.words = np.zeros(n // 64 + 1, np.uint64)
        self.words.view(np.uint8)[: len(packed)] = packed
        self.before = np.concatenate(([0], np.cumsum(np.bitwise_count(self.words), dtype=np.int64)))

    def ones(self, at: np.ndarray) -> np.ndarray:
        w = at >> 6
        low = (np.uint64(1) << (at & 63).astype(np.uint64)) - np.uint64(1)
        return self.before[w] + np.bitwise_count(self.words[w] & low)

    def get(self, at: np.ndarray) -> np.ndarray:
        return (self.words[at >> 6] >> (at & 63).astype(np.uint64) & np.uint64(1)).astype(bool)


class WaveletMatrix:
    """Symbols by bit planes, highest first: access and rank in one walk down the planes."""

    def __init__(self, symbols: np.ndarray, n_symbols: int):
        self.planes: list[tuple[int, BitRanks, int]] = []
        x = symbols
        for shift in range(max(1, (n_symbols - 1).bit_length()) - 1, -1, -1):
            bit = (x >> shift & 1).astype(bool)
            self.planes.append((shift, BitRanks(bit), int((~bit).sum())))
            x = np.concatenate((x[~bit], x[bit]))
        self.origin = self._down(np.arange(n_symbols), np.zeros(n_symbols, np.int64))

    def _down(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        for shift, ranks, zeros in self.planes:
            one = ranks.ones(at)
            at = np.where(symbol >> shift & 1, zeros + one, at - one)
        return at

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """How often each symbol stands before each position."""
        return self._down(symbol, at) - self.origin[symbol]

    def access(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The symbol at each position, and how often it stands before it."""
        symbol = np.zeros(len(at), np.int64)
        for shift, ranks, zeros in self.planes:
            bit, one = ranks.get(at), ranks.ones(at)
            symbol |= bit.astype(np.int64) << shift
            at = np.where(bit, zeros + one, at - one)
        return symbol, at - self.origin[symbol]


def suffix_array(text: np.ndarray, n_symbols: int) -> np.ndarray:
    """Suffixes in order, each ending at its first separator (symbol 0); equal ones by position."""
    n, bits = len(text), max(1, (n_symbols - 1).bit_length())
    span = 62 // bits
    key, open_ = np.zeros(n, np.int64), np.ones(n, bool)
    padded = np.concatenate((text, np.zeros(span, np.int64)))
    for k in range(span):
        s = np.where(open_, padded[k : k + n], 0)
        key = key << bits | s
        open_ &= s > 0
    order = np.argsort(key, kind="stable")
    rank, h = np.empty(n, np.int64), span
    slots, at = np.arange(n), order
    tied = np.concatenate(([False], key[order][1:] == key[order][:-1])) & open_[order]
    head = np.maximum.accumulate(np.where(tied, 0, slots))
    rank[order] = head
    while tied.any():
        more = tied.copy()
        more[:-1] |= tied[1:]
        slots, at, head = slots[more], at[more], head[more]
        second = rank[at + h]
        by = np.lexsort((second, head))
        at, second, group = at[by], second[by], head[by]
        order[slots] = at
        tied = np.concatenate(([False], (second[1:] == second[:-1]) & (group[1:] == group[:-1])))
        head = np.maximum.accumulate(np.where(tied, 0, slots))
        rank[at] = head
        h *= 2
    return order


class FMIndex:
    """Search and locate over one shard's separated text."""

    def __init__(self, text: np.ndarray, n_symbols: int):
        sa = suffix_array(text, n_symbols)
        before = np.concatenate(([0], text[:-1]))
        self.n = len(text)
        self.wavelet = WaveletMatrix(before[sa], n_symbols)
        self.first = np.concatenate(([0], np.cumsum(np.bincount(text, minlength=n_symbols))))
        kept = (sa % SAMPLE == 0) | (before[sa] == 0)
        self.kept, self.samples = BitRanks(kept), sa[kept]

    def search(self, patterns: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Row ranges of right-aligned patterns."""
        width = patterns.shape[1]
        lo, hi = np.zeros(len(lengths), np.int64), np.full(len(lengths), self.n)
        for k in range(width):
            on = np.flatnonzero((lengths > k) & (lo < hi))
            c = patterns[on, width - 1 - k]
            lo[on] = self.first[c] + self.wavelet.rank(c, lo[on])
            hi[on] = self.first[c] + self.wavelet.rank(c, hi[on])
        return lo, np.maximum(lo, hi)

    def locate(self, rows: np.ndarray) -> np.ndarray:
        """Text positions of suffix-array rows."""
        out, walk = np.empty(len(rows), np.int64), np.arange(len(rows))
        rows, steps = rows.copy(), 0
        while len(walk):
            done = self.kept.get(rows)
            out[walk[done]] = self.samples[self.kept.ones(rows[done])] + steps
            walk, rows, steps = walk[~done], rows[~done], steps + 1
            c, before = self.wavelet.access(rows)
            rows = self.first[c] + before
        return out


class Windows:
    """The distinct windows of benchmark items, right-aligned, and the items of each."""

    def __init__(self, items: list[tuple[object, str | None]], width: int = 13):
        self.vocabulary: dict[bytes, int] = {}
        number: dict[str, int] = {}
        found: dict[tuple[int, ...], set[int]] = {}
        for name, text in items:
            ids = [self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words_of(text)]
            for k in range(max(1, len(ids) - width + 1) if ids else 0):
                named = found.setdefault(tuple(ids[k : k + width]), set())
                if name is not None:
                    named.add(number.setdefault(str(name), len(number)))
        self.names = list(number)
        self.lengths = np.array([len(x) for x in found], np.int64)
        self.table = np.zeros((len(found), width), np.int64)
        for k, x in enumerate(found):
            self.table[k, width - len(x) :] = x
        self.item = np.array([i for s in found.values() for i in sorted(s)], np.int64)
        each = np.array([len(s) for s in found.values()], np.int64)
        self.item_at, self.item_n = np.cumsum(each) - each, each
        self.least = int(self.lengths.min()) if len(found) else 0

    def occurrences(self, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Start positions of windows in a shard's words (0: separator), and which window."""
        none = np.zeros(0, np.int64), np.zeros(0, np.int64)
        edge = np.flatnonzero(np.diff(np.concatenate(([0], (words > 0).astype(np.int8), [0]))))
        start, size = edge[::2], edge[1::2] - edge[::2]
        keep = size >= max(1, self.least)
        start, size = start[keep], size[keep]
        if not len(start):
            return none
        place = ragged(start, size + 1)  # each stretch and a separator after it
        text = words[np.minimum(place, len(words) - 1)].copy()
        text[np.cumsum(size + 1) - 1] = 0
        index = FMIndex(text, len(self.vocabulary) + 1)
        lo, hi = index.search(self.table, self.lengths)
        return place[index.locate(ragged(lo, hi - lo))], np.repeat(np.arange(len(lo)), hi - lo)


def merged(start: np.ndarray, end: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Which of n places lie in a span, and the united spans."""
    step = np.zeros(n + 1, np.int64)
    np.add.at(step, start, 1)
    np.add.at(step, end, -1)
    hit = np.cumsum(step[:-1]) > 0
    edge = np.flatnonzero(np.diff(np.concatenate(([0], hit.astype(np.int8), [0]))))
    return hit, edge[::2], edge[1::2]


def search_shard(windows: Windows, docs: list[list[bytes]]) -> tuple[list[list[tuple[int, int]]], list[list[str]]]:
    """Per document of a shard: united spans of words, and names of the items met."""
    get = windows.vocabulary.get
    size = np.array([len(d) for d in docs], np.int64)
    ids = np.fromiter((x for d in docs for x in (*[get(w, 0) for w in d], 0)), np.int64, int(size.sum()) + len(docs))
    begin = np.cumsum(size + 1) - (size + 1)
    at, which = windows.occurrences(ids)
    _, start, end = merged(at, at + windows.lengths[which] if len(at) else at, len(ids))
    spans: list[list[tuple[int, int]]] = [[] for _ in docs]
    for d, a, b in zip(np.searchsorted(begin, start, side="right") - 1, start, end, strict=True):
        spans[d].append((int(a - begin[d]), int(b - begin[d])))
    met: list[list[str]] = [[] for _ in docs]
    if len(at) and windows.names:
        doc = np.searchsorted(begin, at, side="right") - 1
        pair = np.unique(np.repeat(doc, windows.item_n[which]) * len(windows.names) + windows.item[ragged(windows.item_at[which], windows.item_n[which])])
        for p in pair.tolist():
            met[p // len(windows.names)].append(windows.names[p % len(windows.names)])
    return spans, met


SPANS = "doc_id long, text_key long, n_words long, spans array<struct<start:long,end:long>>, items array<string>"


def _pass(docs: DataFrame, windows: Windows, shard_words: int) -> DataFrame:
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    schema = to_arrow_schema(_parse_datatype_string(SPANS))
    shared = docs.sparkSession.sparkContext.broadcast(windows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w, held, n = shared.value, [], 0

        def out():
            spans, met = search_shard(w, [x[2] for x in held])
            rows = {"doc_id": [x[0] for x in held], "text_key": [x[1] for x in held], "n_words": [len(x[2]) for x in held], "spans": [[{"start": a, "end": b} for a, b in s] for s in spans], "items": met}
            held.clear()
            return pa.RecordBatch.from_pydict(rows, schema=schema)

        for ids, keys, texts in slices(batches):
            for i, k, t in zip(ids, keys, texts, strict=True):
                words = words_of(t)
                held.append((i, k, words))
                n += len(words)
                if n >= shard_words:
                    yield out()
                    n = 0
        if held:
            yield out()

    return docs.mapInArrow(run, SPANS)


def item_blocks(benchmark: DataFrame, item: str, text: str, words: int) -> tuple[DataFrame, int]:
    """(item, text, block) of the distinct benchmark rows with text, and the number of blocks of about `words` words."""
    rows = benchmark.select(F.col(item).cast("string").alias("item"), F.col(text).alias("text")).where(F.col("text").isNotNull()).distinct()
    n_words = F.size(F.split("text", r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"))
    total = rows.agg(F.coalesce(F.sum(n_words), F.lit(0))).first()[0]
    blocks = max(1, -(-int(total) // words))
    return rows.withColumn("block", F.pmod(F.xxhash64("item", "text"), F.lit(blocks))), blocks


def contaminated_spans(docs: DataFrame, benchmark: DataFrame, width: int = 13, id_col: str = "doc_id", text: str = "text", item: str = "item_id", item_text: str = "text", shard_words: int = SHARD_WORDS, block_words: int = BLOCK_WORDS) -> DataFrame:
    """(doc_id, n_words, spans, items): removal spans in words, united, and the items met."""
    rows = docs.select(F.col(id_col).alias("doc_id"), F.xxhash64(text).alias("text_key"), F.col(text).alias("text"))
    dealt, blocks = item_blocks(benchmark, item, item_text, block_words)

    def windows(b: int) -> Windows:
        return Windows([(r["item"], r["text"]) for r in dealt.where(F.col("block") == b).select("item", "text").toLocalIterator()], width)

    if blocks == 1:
        return _pass(rows, windows(0), shard_words).select("doc_id", "n_words", "spans", "items")
    scratch = Scratch(docs.sparkSession, "fmindex")
    dealt = scratch.write(dealt, "items")
    found = functools.reduce(DataFrame.unionByName, [scratch.write(_pass(rows, windows(b), shard_words), "pass") for b in range(blocks)])
    found = found.groupBy("doc_id", "text_key", "n_words").agg(F.flatten(F.collect_list("spans")).alias("spans"), F.array_distinct(F.flatten(F.collect_list("items"))).alias("items"), (F.count("*") / blocks).cast("int").alias("copies"))

    def make():
        def f(ids, n_words, spans, items, copies):
            out = {"doc_id": [], "n_words": [], "spans": [], "items": []}
            for i, n, s, m, c in zip(ids, n_words, spans, items, copies, strict=True):
                _, a, b = merged(np.array([x["start"] for x in s], np.int64), np.array([x["end"] for x in s], np.int64), n)
                for _ in range(c):
                    for k, v in zip(out, (i, n, [{"start": x, "end": y} for x, y in zip(a.tolist(), b.tolist(), strict=True)], m), strict=True):
                        out[k].append(v)
            return out

        return f

    return map_rows(found.select("doc_id", "n_words", "spans", "items", "copies"), make, "doc_id long, n_words long, spans array<struct<start:long,end:long>>, items array<string>")


def verdicts(found: DataFrame) -> DataFrame:
    """Digest columns: hit words, items, and the contamination rule (some hit, and a twentieth of the words)."""
    hit = F.aggregate("spans", F.lit(0).cast("long"), lambda a, s: a + s["end"] - s["start"])
    return found.withColumn("n_hit", hit).select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join(F.array_sort("items"), ","), 256).alias("items_sha256"),
        ((F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words"))).alias("contaminated"), "spans",
    )
