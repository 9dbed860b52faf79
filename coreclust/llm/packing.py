"""Best-fit packing of tokenised documents into sequences of a fixed length.

Only lengths matter to the search, and there are at most `size` of them, so the search runs on
the histogram of lengths: bin completion by branch and bound.  The largest remaining length is
completed by its undominated fillings, least waste first, each applied to as many sequences as
the counts allow and, when all have failed, to fewer; a branch ends when its waste exceeds what a better packing could afford.  Best-fit decreasing
gives the first incumbent, and the search stops at a lower bound or after `NODES` steps, with
the best packing so far.  Pieces then find their place from their rank within their length.

Edge cases.  Null text counts as empty: one piece with the closing id.  Longer documents are
cut into full pieces, the first taking what is over.  Repeated rows are packed as often as
they occur.  An empty table gives no rows.
"""

from __future__ import annotations

import functools
import itertools
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import SETTLED, vocabulary_of
from .common import Scratch, map_rows, tokenizer_path

SIZE = 2048
#: Steps of the search before the incumbent is taken.
NODES = 20_000
#: Steps whose choices are held at a time; a choice among 2,048 lengths is half a megabyte.
OPEN = 64
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


@functools.lru_cache(maxsize=2)
def encoder(vocabulary: str) -> Encoder:
    """One encoder per worker process, whatever the number of its tasks."""
    return Encoder(vocabulary)


class Encoder:
    """Token ids as the tokenizers library gives them.

    Texts in settled scripts go through a faster library that shares the merge table (same ids,
    tested); all others through the tokenizers library itself.
    """

    def __init__(self, vocabulary: str):
        import tiktoken

        self.v = vocabulary_of(tokenizer_path(vocabulary))
        self.fast = tiktoken.Encoding("pieces", pat_str=PATTERN, mergeable_ranks=self.v.token_bytes(), special_tokens=self.v.special_ids)

    def ids(self, text: str) -> np.ndarray:
        if len(text) < 200_000 and not SETTLED.search(text):
            return np.array(self.fast.encode(text, allowed_special="all"), np.uint32)
        return np.array(self.v.library().encode(text, add_special_tokens=False).ids, np.uint32)


def pieces(docs: DataFrame, vocabulary: str = "byte_bpe_50k.json", size: int = SIZE, close: int = 0, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32): each document's ids, closed and cut."""

    def make():
        enc = encoder(vocabulary)

        def f(ids, texts):
            out = {"doc_id": [], "piece": [], "start": [], "length": [], "ids_crc32": []}
            for i, t in zip(ids, texts, strict=True):
                x = np.append(enc.ids(t or ""), np.uint32(close)).astype("<u4")
                first = len(x) % size or size
                cuts = [0, *range(first, len(x) + 1, size)]
                for k, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)):
                    for name, value in zip(out, (i, k, a, b - a, zlib.crc32(x[a:b].tobytes())), strict=True):
                        out[name].append(value)
            return out

        return f

    return map_rows(docs.select(F.col(id_col).alias("doc_id"), F.col(text).alias("text")), make, "doc_id long, piece int, start long, length long, ids_crc32 long")


def lower_bound(counts: np.ndarray, size: int) -> int:
    """Sequences needed at least: total length, and for each cut t the lengths over size - t alone plus what their gaps cannot hold."""
    n, at = counts.astype(np.int64), np.arange(len(counts))
    total = int((n * at).sum())
    best = -(-total // size)
    for t in range(1, size // 2 + 1):
        big, half, small = n[size - t + 1 :].sum(), slice(size // 2 + 1, size - t + 1), slice(t, size // 2 + 1)
        gap = n[half].sum() * size - (n[half] * at[half]).sum()
        best = max(best, int(big + n[half].sum() + max(0, -(-((n[small] * at[small]).sum() - gap) // size))))
    return best


def best_fit(counts: np.ndarray, size: int) -> list[tuple[dict[int, int], int]]:
    """Best-fit decreasing over counts: (lengths in a sequence, how many such sequences)."""
    bins: dict[int, list[tuple[dict[int, int], int]]] = {}  # by room left

    def put(room, fill, m):
        if m:
            bins.setdefault(room, []).append((fill, m))

    for x in range(size, 0, -1):
        n = int(counts[x])
        for room in sorted(r for r in bins if r >= x):
            for fill, m in bins.pop(room) if n else ():
                q = room // x
                whole = min(m, n // q)
                put(room - q * x, fill | {x: q}, whole)
                n -= whole * q
                if whole < m and n:
                    put(room - n * x, fill | {x: n}, 1)
                    whole, n = whole + 1, 0
                put(room, fill, m - whole)
            if not n:
                break
        q = size // x
        put(size - q * x, {x: q}, n // q)
        if n % q:
            put(size - n % q * x, {x: n % q}, 1)
    return [b for group in bins.values() for b in group]


def _sums(items: list[tuple[int, int]], room: int) -> list[int]:
    """For each position, the sums up to `room` that the items (length, count) from there on can make, as bits."""
    out, bits, mask = [1], 1, (1 << room + 1) - 1
    for x, n in reversed(items):
        n, q = min(n, room // x), 1
        while n:
            q = min(q, n)
            bits |= bits << q * x & mask
            n, q = n - q, 2 * q
        out.append(bits)
    return out[::-1]


def _dominated(fill: dict[int, int], counts: np.ndarray, room: int) -> bool:
    """Whether one item beside the filling can take the place of some of its own that are not longer in sum."""
    waste = room - sum(x * q for x, q in fill.items())
    sums, more = 1, 0  # of any items, of two or more
    for x, q in fill.items():
        for _ in range(q):
            more |= more << x | (sums & ~1) << x
            sums |= sums << x
    spare = np.flatnonzero(counts[: room + 1])
    for y in spare[spare > 0].tolist():
        if counts[y] > fill.get(y, 0) and (more >> y & 1 or sums >> max(0, y - waste) & (1 << min(y, waste)) - 1):
            return True
    return False


def fillings(counts: np.ndarray, room: int, waste: int | None = None) -> Iterator[dict[int, int]]:
    """All undominated ways to fill `room`, in the order of `every_filling`.

    A filling is dominated where an item beside it fits in place of some of its items (or into the waste).
    """
    return (f for f in every_filling(counts, room, waste) if not _dominated(f, counts, room))


def every_filling(counts: np.ndarray, room: int, waste: int | None = None) -> Iterator[dict[int, int]]:
    """All ways to fill `room` with at most `waste` of it idle, least waste first, then larger items first."""
    items = [(int(x), int(counts[x])) for x in np.flatnonzero(counts[: room + 1])[::-1] if x]
    reach = _sums(items, room)

    def exact(at: int, left: int) -> Iterator[dict[int, int]]:
        stack = [(at, left, ())]
        while stack:
            at, left, took = stack.pop()
            if not left:
                yield dict(took)
                continue
            while at < len(items) and items[at][0] > left:
                at += 1
            if not reach[at] >> left & 1:
                continue
            x, n = items[at]
            for q in range(min(n, left // x) + 1):  # the last one pushed, the most of the longest, comes first
                if reach[at + 1] >> left - q * x & 1:
                    stack.append((at + 1, left - q * x, (*took, (x, q)) if q else took))

    for idle in range(min(room, room if waste is None else waste) + 1):
        if reach[0] >> room - idle & 1:
            yield from exact(0, room - idle)


class _Options:
    """Choices of a step, and how many of them were taken: those of steps far above are forgotten, and made anew on the way back."""

    def __init__(self, choices: Iterator):
        self.choices, self.taken = choices, 0

    def __iter__(self) -> Iterator:
        return self

    def __next__(self):
        got = next(self.choices)
        self.taken += 1
        return got


def bin_completion(counts: np.ndarray, size: int = SIZE, nodes: int = NODES, width: int | None = None) -> list[tuple[dict[int, int], int]]:
    """Packing of `counts[length]` items, as (lengths in a sequence, number of such sequences).

    `width` bounds the fillings of a step; by default all are tried.
    """
    counts = counts.astype(np.int64).copy()
    best = best_fit(counts, size)
    used = sum(m for _, m in best)
    need = lower_bound(counts, size)
    total = int((counts * np.arange(len(counts))).sum())
    path: list[tuple[dict[int, int], int, _Options]] = []  # filling, times, choices not tried yet
    waste, n_bins = 0, 0

    def choices(x: int) -> Iterator[tuple[dict[int, int], int]]:
        whole, now = counts.copy(), counts.copy()
        now[x] -= 1

        def undominated() -> Iterator[dict[int, int]]:
            nonlocal tried
            for f in every_filling(now, size - x, (used - 1) * size - total - waste):
                if not _dominated(f, now, size - x):
                    yield f
                    continue
                tried += 1
                if tried >= nodes:
                    return

        def applied(fewer: bool) -> Iterator[tuple[dict[int, int], int]]:
            for f in itertools.islice(undominated(), width):
                fill = f | {x: f.get(x, 0) + 1}
                most = min(int(whole[y]) // q for y, q in fill.items())
                for times in range(most - 1, 0, -1) if fewer else (most,):
                    yield fill, times

        yield from applied(False)
        yield from applied(True)

    def step(options: _Options) -> bool:
        nonlocal waste, n_bins, tried
        for fill, times in options:
            idle = (size - sum(x * q for x, q in fill.items())) * times
            if waste + idle <= (used - 1) * size - total:
                for x, q in fill.items():
                    counts[x] -= q * times
                waste, n_bins = waste + idle, n_bins + times
                path.append((fill, times, options))
                if len(path) > OPEN:
                    path[-1 - OPEN][2].choices = None
                return True
            tried += 1
            if tried >= nodes:
                return False
        return False

    def undo() -> _Options:
        nonlocal waste, n_bins, tried
        fill, times, options = path.pop()
        for x, q in fill.items():
            counts[x] += q * times
        waste -= (size - sum(x * q for x, q in fill.items())) * times
        n_bins -= times
        if options.choices is None:
            before, tried = tried, 0  # what was counted once does not count again
            options.choices = choices(int(np.flatnonzero(counts)[-1]))
            for _ in range(options.taken):
                next(options.choices, None)
            tried = before
        return options

    tried, options = 0, None
    while used > need and tried < nodes:
        tried += 1
        if options is None:
            top = np.flatnonzero(counts)
            if not len(top):
                if n_bins < used:
                    used, best = n_bins, [(f, t) for f, t, _ in path]
                options = _Options(iter(()))
            else:
                options = _Options(choices(int(top[-1])))
        if step(options):
            options = None
        elif path:
            options = undo()
        else:
            break
    return best


def slots(plan: list[tuple[dict[int, int], int]], size: int = SIZE) -> dict[str, np.ndarray]:
    """The plan by length and rank: from which rank on, which sequence, which offset, how many to a sequence.

    A plan's fillings each use up a length, and a filling has at most 63 different ones, so this
    table stays under 130,000 rows whatever the number of documents.
    """
    rows, seen, at = [], {}, 0
    for fill, times in plan:
        offset = 0
        for x, q in sorted(fill.items(), reverse=True):
            rows.append((x << 44 | seen.get(x, 0), at, offset, q))
            seen[x] = seen.get(x, 0) + q * times
            offset += x * q
        at += times
    rows.sort()
    return dict(zip(("key", "sequence", "offset", "each"), np.array(rows, np.int64).reshape(-1, 4).T, strict=True))


def pack(docs: DataFrame, vocabulary: str = "byte_bpe_50k.json", size: int = SIZE, id_col: str = "doc_id", text: str = "text", nodes: int = NODES) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, sequence_id, offset) of every piece."""
    spark = docs.sparkSession
    cut = Scratch(spark, "packing").write(pieces(docs, vocabulary, size, id_col=id_col, text=text), "pieces")
    counts = np.zeros(size + 1, np.int64)
    for x, n in cut.groupBy("length").count().collect():  # at most `size` rows
        counts[x] = n
    table = slots(bin_completion(counts, size, nodes), size)
    salts = max(8, int(counts.sum()) // 100_000)
    salted = cut.withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(salts)).cast("int"))
    before = salted.groupBy("length", "salt").agg(F.count("*").alias("n"))
    before = before.select("length", "salt", (F.sum("n").over(Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, 0)) - F.col("n")).alias("before"))
    near = Window.partitionBy("length", "salt").orderBy("doc_id", "piece", "ids_crc32")
    ranked = salted.withColumn("near", F.row_number().over(near)).join(before, ["length", "salt"])
    ranked = ranked.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("before") + F.col("near") - 1).alias("rank"))
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            length, rank = (b.column(k).to_numpy(zero_copy_only=False) for k in (3, 5))
            key = length << 44 | rank
            row = np.searchsorted(table["key"], key, side="right") - 1
            past = key - table["key"][row]
            sequence = table["sequence"][row] + past // table["each"][row]
            offset = table["offset"][row] + past % table["each"][row] * length
            yield pa.RecordBatch.from_arrays([*b.columns[:5], pa.array(sequence), pa.array(offset)], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return ranked.mapInArrow(place, schema)
