"""Interpolated modified Kneser-Ney language model, counted in Spark and looked up in sorted hash arrays.

Documents are gathered into blocks of a bounded number of tokens.  For each order, from the
highest down, a block sends the sorted hashes of its distinct n-grams with its own counts, cut
by hash range, to shards.  A shard merges them into one sorted hash array with totals, which it
memory-maps, and answers every block with the totals of exactly the n-grams that the block
asked for.  So no task ever holds the model: a block holds what its own texts need, a shard its
hash range, and hash ranges are even whatever n-gram is frequent.

Continuation counts and context totals need every distinct n-gram once.  A shard names one
block as an n-gram's owner, and the owner counts it towards its suffix and its context in the
next lower order.

The rows (order, shard, keys, totals) are the stored model; `fit` returns them, and `score`
treats a stored model like one more block that only answers.

Edge cases.  Null text counts as empty: one token, the end.  A null id is scored and never
learned from unless the learning condition says so.  Unknown words share the uniform
probability 1 / (V + 1).  Without learned text every order falls back to that.  Discounts that
the counts of counts cannot give (too little text) are 0.5, 1 and 1.5.  Repeated rows count and
are scored each.  Texts are read whole; a document longer than a block is a block of its own.
"""

from __future__ import annotations

import shutil
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import LOWER, Scratch, encode, ensure_file_dir, slices

BLOCK_TOKENS, SHARD_TOKENS = 600_000, 300_000
#: Shards, and blocks, that one task of an exchange gets; exchanges have as many tasks as that takes, so none grows with the corpus.
DEALT = 4
START, END = np.uint64(0x5354415254), np.uint64(0x454E44)
ODD = np.uint64(0x9E3779B97F4A7C15)
#: Payload columns: adjusted count; then, as context of the next order: total, and continuations seen 1, 2, 3 or more times; raw count.
ADJUSTED, TOTAL, ONE, TWO, MANY, RAW = range(6)
STORE = "block string, n_tokens long, doc_ids array<long>, train array<boolean>, lens array<int>, vocab binary, seq binary"
SENT = "shard long, block string, keys binary, cols array<binary>"
REPLY = "block string, shard long, cols array<binary>, stats array<long>"


def packed(x: np.ndarray) -> bytes:
    """Unsigned numbers as compressed byte planes."""
    return zstandard.compress(np.ascontiguousarray(x.astype("<u8").view(np.uint8).reshape(-1, 8).T).tobytes(), 1)


def unpacked(blob: bytes) -> np.ndarray:
    raw = np.frombuffer(zstandard.decompress(blob), np.uint8)
    return np.ascontiguousarray(raw.reshape(8, -1).T).view("<u8").ravel() if len(raw) else np.zeros(0, np.uint64)


def ascending(x: np.ndarray) -> bytes:
    return packed(np.diff(x, prepend=np.uint64(0)))


def from_ascending(blob: bytes) -> np.ndarray:
    return np.cumsum(unpacked(blob), dtype=np.uint64)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)


def _schema(text: str) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    return to_arrow_schema(_parse_datatype_string(text))


def blocks(docs: DataFrame, learn: Column, id_col: str = "doc_id", text: str = "text", size: int = BLOCK_TOKENS) -> DataFrame:
    """One row per block: its documents, its sorted word hashes, and its tokens as places among them."""
    schema = _schema(STORE)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, made, held, n = TaskContext.get().partitionId(), 0, [], 0

        def out():
            nonlocal made
            vocab, seq = np.unique(np.concatenate([h for *_, h in held]), return_inverse=True)
            made += 1
            row = {"block": f"{part}-{made}", "n_tokens": n, "doc_ids": [x[0] for x in held], "train": [x[1] for x in held], "lens": [len(x[2]) for x in held], "vocab": ascending(vocab), "seq": zstandard.compress(np.ascontiguousarray(seq.astype("<u4").view(np.uint8).reshape(-1, 4).T).tobytes(), 1)}
            held.clear()
            return pa.RecordBatch.from_pylist([row], schema=schema)

        for ids, trains, texts in slices(batches):
            for i, train, t in zip(ids, trains, texts, strict=True):
                words = encode(t).translate(LOWER).split()
                h = np.empty(len(words) + 2, np.uint64)
                h[0], h[-1] = START, END
                h[1:-1] = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
                held.append((i, bool(train), h))
                n += len(words) + 1
                if n >= size:
                    yield out()
                    n = 0
        if held:
            yield out()

    rows = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(learn, F.lit(False)).alias("train"), F.col(text).alias("text"))
    return rows.mapInArrow(run, STORE)


class Block:
    """A block's n-grams by order: sorted distinct hashes, and which one ends at each place."""

    def __init__(self, row: dict):
        self.doc_ids, lens = row["doc_ids"], np.array(row["lens"], np.int64)
        vocab = from_ascending(row["vocab"])
        raw = np.frombuffer(zstandard.decompress(row["seq"]), np.uint8)
        seq = np.ascontiguousarray(raw.reshape(4, -1).T).view("<u4").ravel().astype(np.int64)
        self.doc = np.repeat(np.arange(len(lens)), lens)
        self.at = np.arange(len(seq)) - np.repeat(np.cumsum(lens) - lens, lens)
        self.train = np.array(row["train"], bool)[self.doc]
        self.keys, self.index = {1: vocab}, {1: seq}
        self.hash = {1: vocab[seq]}
        self.first: dict[int, np.ndarray] = {}

    def grams(self, k: int) -> None:
        """Order k: `index` holds, for each place that ends a k-gram, its place among `keys`."""
        if k in self.keys:
            return
        self.grams(k - 1)
        h = np.zeros(len(self.at), np.uint64)
        h[1:] = _mix(self.hash[k - 1][:-1] * ODD + self.hash[1][1:] + np.uint64(k))
        on = np.flatnonzero(self.at >= k - 1)
        keys, first, where = np.unique(h[on], return_index=True, return_inverse=True)
        self.hash[k], self.keys[k], self.first[k] = h, keys, on[first]
        self.index[k] = np.zeros(len(self.at), np.int64)
        self.index[k][on] = where

    def own_counts(self, k: int) -> np.ndarray:
        on = self.train & (self.at >= max(1, k - 1))
        return np.bincount(self.index[k][on], minlength=len(self.keys[k]))

    def payload(self, k: int, order: int, above: list[np.ndarray] | None) -> list[np.ndarray]:
        """What this block adds to its order-k n-grams; `above` is the reply for order k + 1."""
        self.grams(k)
        if k == order:
            cols = [self.own_counts(k)]
        else:
            self.grams(k + 1)
            n, total = len(self.keys[k]), (above[ADJUSTED] >> np.uint64(1)).astype(np.int64)
            mine = np.flatnonzero((above[ADJUSTED] & np.uint64(1)).astype(bool) & (total > 0))
            end, total = self.first[k + 1][mine], total[mine]
            adjusted = np.bincount(self.index[k][end], minlength=n)
            if k > 1:  # n-grams at the start of a text have nothing before them to count
                opening = self.at[self.first[k]] == k - 1
                adjusted = np.where(opening, self.own_counts(k), adjusted)
            context = self.index[k][end - 1]
            cols = [adjusted, np.bincount(context, total, n), *(np.bincount(context[x], minlength=n) for x in (total == 1, total == 2, total > 2))]
        if k == 1:
            cols += [np.zeros(len(cols[0]), np.int64)] * (RAW - len(cols)) + [self.own_counts(1)]
        return cols

    def requests(self, name: str, k: int, cols: list[np.ndarray], shards: int) -> Iterator[dict]:
        keys = self.keys[k]
        shard = ((keys >> np.uint64(32)) * np.uint64(shards)) >> np.uint64(32)
        cut = np.concatenate(([0], np.flatnonzero(np.diff(shard)) + 1, [len(keys)]))
        for a, b in zip(cut, cut[1:], strict=False):
            if a < b:
                yield {"shard": int(shard[a]), "block": name, "keys": ascending(keys[a:b]), "cols": [packed(c[a:b].astype(np.uint64)) for c in cols]}


def _answered(table: pa.Table) -> list[np.ndarray]:
    """A block's replies of one order, in the order of its keys."""
    rows = sorted(table.to_pylist(), key=lambda r: r["shard"])
    return [np.concatenate([unpacked(r["cols"][c]) for r in rows]) for c in range(len(rows[0]["cols"]))]


def answer(group: pa.Table, keep_model: bool = False) -> Iterator[dict]:
    """One shard: merged sorted hashes, memory-mapped, and a reply to each block."""
    rows = group.to_pylist()
    asked = [from_ascending(r["keys"]) for r in rows]
    every = np.concatenate(asked)
    order = np.argsort(every, kind="stable")
    every = every[order]
    head = np.flatnonzero(np.concatenate(([True], every[1:] != every[:-1])))
    cols = [np.add.reduceat(np.concatenate([unpacked(r["cols"][c]) for r in rows])[order], head) for c in range(len(rows[0]["cols"]))]
    source = np.repeat(np.arange(len(rows)), [len(a) for a in asked])[order]
    counted = np.concatenate([unpacked(r["cols"][ADJUSTED]) for r in rows])[order] > 0
    owner = np.minimum.reduceat(np.where(counted, source, len(rows)), head)
    folder = ensure_file_dir()
    try:
        np.save(f"{folder}/keys.npy", every[head])
        np.save(f"{folder}/cols.npy", np.stack(cols))
        keys, totals = np.load(f"{folder}/keys.npy", mmap_mode="r"), np.load(f"{folder}/cols.npy", mmap_mode="r")
        a = cols[ADJUSTED]
        stats = [int((a == x).sum()) for x in (1, 2, 3, 4)] + [int((a > 0).sum()), int(a.sum())]
        stats += [int((cols[RAW] > 0).sum()), int(cols[RAW].sum())] if len(cols) > RAW else [0, 0]
        yield {"block": None, "shard": rows[0]["shard"], "cols": [ascending(every[head]), *map(packed, cols)] if keep_model else [], "stats": stats}
        for k, (r, mine) in enumerate(zip(rows, asked, strict=True)):
            if r["block"] is None:
                continue  # a stored model asks nothing
            at = np.searchsorted(keys, mine)
            got = [np.asarray(totals[c][at]) for c in range(len(cols))]
            got[ADJUSTED] = got[ADJUSTED] << np.uint64(1) | (owner[at] == k).astype(np.uint64)
            yield {"block": r["block"], "shard": r["shard"], "cols": [packed(g) for g in got], "stats": []}
        del keys, totals
    finally:
        shutil.rmtree(folder, ignore_errors=True)


@dataclass
class Order:
    """Corpus-wide figures of one order: counts of adjusted counts, and the discounts they give."""

    stats: list[int]

    def discounts(self) -> np.ndarray:
        n = self.stats[:4]
        if min(n) == 0:
            return np.array([0, 0.5, 1.0, 1.5])
        y = n[0] / (n[0] + 2 * n[1])
        d = [k - (k + 1) * y * n[k] / n[k - 1] for k in (1, 2, 3)]
        return np.array([0.0, *(min(max(x, 0.01), k - 0.001) if x > 0 else 0.5 * k for k, x in enumerate(d, 1))])


def _scored(block: Block, replies: dict[int, list[np.ndarray]], orders: dict[int, Order], order: int) -> dict:
    on = np.flatnonzero(block.at > 0)
    doc, n_docs = block.doc[on], len(block.doc_ids)
    known_words, all_tokens = orders[1].stats[6:8]
    got = replies[1]
    adjusted = (got[ADJUSTED] >> np.uint64(1)).astype(np.int64)
    raw = got[RAW].astype(np.int64)
    one = block.index[1][on]
    c = raw[one]
    d, mass = orders[1].discounts(), max(1, orders[1].stats[5])
    n1, n2 = orders[1].stats[:2]
    free = (d[1] * n1 + d[2] * n2 + d[3] * (orders[1].stats[4] - n1 - n2)) / mass if orders[1].stats[5] else 1.0
    p = (adjusted - d[np.minimum(adjusted, 3)])[one] / mass + free / (known_words + 1)
    for k in range(2, order + 1):
        block.grams(k)
        here = np.flatnonzero(block.at[on] >= k - 1)
        a = (replies[k][ADJUSTED] >> np.uint64(1)).astype(np.int64)[block.index[k][on[here]]]
        context = block.index[k - 1][on[here] - 1]
        total, *n = (replies[k - 1][x].astype(np.int64)[context] for x in (TOTAL, ONE, TWO, MANY))
        d = orders[k].discounts()
        seen = total > 0
        here, a, total = here[seen], a[seen], total[seen]
        back = sum(d[x + 1] * n[x][seen] for x in range(3)) / total
        p[here] = (a - d[np.minimum(a, 3)]) / total + back * p[here]
    add = lambda x: np.bincount(doc, x, n_docs)
    n_tokens = np.bincount(doc, minlength=n_docs)
    return {
        "doc_id": block.doc_ids, "n_tokens": n_tokens, "n_known": np.bincount(doc, c > 0, n_docs).astype(np.int64), "train_tokens": [all_tokens] * n_docs,
        "base_score": add(np.log10(c + 1.0)) - n_tokens * np.log10(all_tokens + known_words + 1.0), "score": add(np.log10(p)),
    }


SCORES = "doc_id long, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def _dealt(rows: DataFrame, key: str, groups: int) -> DataFrame:
    """`rows` exchanged by a key with so many groups."""
    return rows.repartition(max(rows.sparkSession.sparkContext.defaultParallelism, -(-groups // DEALT)), key)


def _merge(sent: DataFrame, keep_model: bool, shards: int) -> DataFrame:
    schema = _schema(REPLY)
    return _dealt(sent, "shard", shards).groupBy("shard").applyInArrow(lambda t: pa.Table.from_pylist(list(answer(t, keep_model)), schema=schema), REPLY)


def _orders(replies: DataFrame) -> Order:
    row = replies.where("block IS NULL").select(*[F.sum(F.col("stats")[i]).alias(f"s{i}") for i in range(8)]).first()
    return Order([int(x or 0) for x in row])


def _joined(store: DataFrame, replies: dict[int, DataFrame]) -> DataFrame:
    """Rows of each block together: its own, and the replies by order."""
    out = store.select("block", F.lit(0).alias("order"), F.lit(0).cast("long").alias("shard"), F.struct("doc_ids", "train", "lens", "vocab", "seq").alias("own"), F.lit(None).cast("array<binary>").alias("cols"))
    for k, r in replies.items():
        out = out.unionByName(r.where("block IS NOT NULL").select("block", F.lit(k).alias("order"), "shard", F.lit(None).cast(out.schema["own"].dataType).alias("own"), "cols"))
    return out


def _opened(table: pa.Table) -> tuple[Block, dict[int, list[np.ndarray]]]:
    order = table.column("order").to_numpy()
    own = table.take(np.flatnonzero(order == 0)).column("own")[0].as_py()
    return Block(own), {int(k): _answered(table.take(np.flatnonzero(order == k)).select(["shard", "cols"])) for k in np.unique(order[order > 0])}


def _first_requests(k: int, shards: int):
    schema = _schema(SENT)

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                (row,) = batch.slice(i, 1).to_pylist()
                b = Block(row)
                yield pa.RecordBatch.from_pylist(list(b.requests(row["block"], k, b.payload(k, k, None), shards)), schema=schema)

    return first


def _lower_requests(k: int, order: int, shards: int):
    schema = _schema(SENT)

    def lower(t: pa.Table) -> pa.Table:
        b, got = _opened(t)
        return pa.Table.from_pylist(list(b.requests(t.column("block")[0].as_py(), k, b.payload(k, order, got[k + 1]), shards)), schema=schema)

    return lower


def run(docs: DataFrame, learn: Column, order: int = 2, id_col: str = "doc_id", text: str = "text", model: dict[int, DataFrame] | None = None, keep_model: bool = False, block_tokens: int = BLOCK_TOKENS, shard_tokens: int = SHARD_TOKENS) -> tuple[DataFrame, dict[int, DataFrame]]:
    """Scores of every document and, with `keep_model`, the model's rows by order."""
    scratch = Scratch(docs.sparkSession, "kneserney")
    store = scratch.write(blocks(docs, learn, id_col, text, block_tokens), "blocks")
    tokens, n_blocks = store.agg(F.coalesce(F.sum("n_tokens"), F.lit(0)), F.count("*")).first()
    shards = max(1, int(tokens) // shard_tokens)
    if model:
        shards = next(iter(model.values())).agg(F.max("shards")).first()[0]
    replies, orders, kept = {}, {}, {}
    for k in range(order, 0, -1):
        if k == order:
            sent = store.mapInArrow(_first_requests(k, shards), SENT)
        else:
            sent = _dealt(_joined(store, {k + 1: replies[k + 1]}), "block", n_blocks).groupBy("block").applyInArrow(_lower_requests(k, order, shards), SENT)
        if model:
            sent = sent.unionByName(model[k].select("shard", F.lit(None).cast("string").alias("block"), "keys", "cols"))
        replies[k] = scratch.write(_merge(sent, keep_model, shards), f"order{k}")
        orders[k] = _orders(replies[k])
        kept[k] = replies[k].where("block IS NULL").select("shard", F.lit(shards).alias("shards"), F.col("cols")[0].alias("keys"), F.slice("cols", F.lit(2), F.size("cols") - 1).alias("cols"))
    score_schema = _schema(SCORES)

    def last(t: pa.Table) -> pa.Table:
        b, got = _opened(t)
        return pa.Table.from_pydict(_scored(b, got, orders, order), schema=score_schema)

    return _dealt(_joined(store, replies), "block", n_blocks).groupBy("block").applyInArrow(last, SCORES), kept


def fit(docs: DataFrame, learn: Column | None = None, order: int = 2, **options) -> dict[int, DataFrame]:
    """The model's rows (shard, shards, keys, cols) by order: sorted hash arrays and their totals."""
    return run(docs, F.lit(True) if learn is None else learn, order, keep_model=True, **options)[1]


def score(docs: DataFrame, model: dict[int, DataFrame], **options) -> DataFrame:
    """Scores of `docs` by a stored model."""
    return run(docs, F.lit(False), max(model), model=model, **options)[0]


def perplexity(scores: DataFrame, column: str = "score") -> Column:
    return F.pow(F.lit(10.0), -F.sum(column) / F.sum("n_tokens"))
