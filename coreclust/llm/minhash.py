"""Near-duplicate groups by one-permutation hashing with optimal densification.

One hash of every shingle falls into one of 128 bins; a bin's least hash is its entry, and an
empty bin takes the entry of the first filled bin on its own random walk.  32 bands of four
bins make buckets.  Each bucket gives star-shaped candidate edges, from its smallest document
to those that resemble it.  Documents of a bucket that are not close to its centre get further
centres, until none is left: large buckets in rounds, the others within one task.

Stars alone could lose a link between two documents that are both unlike the centre.  So
candidates are gathered into clusters, and clusters are settled on full shingle sets: blocks
of bounded size against themselves and against the cluster's hubs first; then, where a cluster
still has several components, the documents outside its largest component against every block.
Equal sets are one document until the end, and only spanning edges leave a task.

A link needs similarity of at least 80 %.  A pair at exactly that similarity misses all bands
with probability (1 - 0.8^4)^32 = 5e-8.

Edge cases.  Null text, or no words: an empty set, linked with nothing.  Fewer words than a
shingle: the whole sequence is the only shingle.  Equal rows fall together.  A null id keeps
its row, with the component of its set.  Empty tables give no rows.
"""

from __future__ import annotations

import functools

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import LOWER, Scratch, default_parallelism, encode, map_rows, slices
from .components import components

BINS, ROWS = 128, 4
WALK = 4096
#: Estimated similarity to a bucket's centre below which the bucket met by chance.
CHANCE = 0.4
#: Estimated similarity to a centre from which on a document needs no other one: whatever shares 0.6 of its bins has CHANCE there.
CLOSE = CHANCE + 0.4
#: Members of a bucket that are left for one task, and rounds of centres for larger ones before these go in pairs of pieces.
LOCAL, STARS = 512, 6
#: Documents and shingles of a block, hubs of a cluster, queries in a group.
BLOCK, BLOCK_SHINGLES, HUBS, QUERIES = 128, 1_000_000, 16, 128
#: Bits of the filter of wanted ids, at most, as a power of two.
MEMBER_BITS = 26
ODD = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F)


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingles(text: str | None, width: int = 4) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the word shingles."""
    words = encode(text).translate(LOWER).split()
    if not words:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
    width = min(width, len(h))
    n = len(h) - width + 1
    x = np.full(n, width, np.uint64)
    for k in range(width):
        x = _mixed(x * np.uint64(ODD[k % 5]) + h[k : k + n])
    return np.unique(x)


class Sketcher:
    def __init__(self):
        step = np.arange(BINS, dtype=np.uint64)[:, None] << np.uint64(32) | np.arange(WALK, dtype=np.uint64)[None, :]
        self.walk = (_mixed(step * np.uint64(ODD[3]) + np.uint64(ODD[4])) % np.uint64(BINS)).astype(np.int16)
        self.edges = np.arange(BINS, dtype=np.uint64) << np.uint64(57)
        self.band = np.arange(BINS // ROWS, dtype=np.uint64)

    def bins(self, s: np.ndarray) -> np.ndarray:
        """Densified entries of the sorted hashes `s` (not empty)."""
        at = np.searchsorted(s, self.edges)
        filled = (np.append(at[1:], len(s)) - at) > 0
        out = s[np.minimum(at, len(s) - 1)]
        empty, a, block = np.flatnonzero(~filled), 0, 64
        while len(empty) and a < WALK:
            met = filled[self.walk[empty, a : a + block]]
            have = met.any(1)
            e = empty[have]
            out[e] = out[self.walk[e, a + met[have].argmax(1)]]
            empty, a, block = empty[~have], a + block, min(block * 4, 1024)
        if len(empty):
            out[empty] = out[np.flatnonzero(filled)[0]]
        return out

    def sketch(self, s: np.ndarray) -> tuple[list[int], bytes]:
        v = _mixed(self.bins(s))
        key = self.band + np.uint64(1)
        for k in range(ROWS):
            key = _mixed(key * np.uint64(ODD[k]) + v[k::ROWS])
        return key.view(np.int64).tolist(), (v >> np.uint64(24)).astype(np.uint8).tobytes()


def sketches(docs: DataFrame, width: int = 4, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n, set_key, sig, bands): set size, digest of the set, a byte per bin, bucket keys."""

    def make():
        k = Sketcher()

        def f(ids, texts):
            out = {"doc_id": ids, "n": [], "set_key": [], "sig": [], "bands": []}
            for t in texts:
                s = shingles(t, width)
                bands, sig = k.sketch(s) if len(s) else (None, None)
                for name, value in zip(("n", "set_key", "sig", "bands"), (len(s), xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None, sig, bands), strict=True):
                    out[name].append(value)
            return out

        return f

    return map_rows(docs.select(F.col(id_col).alias("doc_id"), F.col(text).alias("text")), make, "doc_id long, n long, set_key binary, sig binary, bands array<long>")


def _starred(members: DataFrame, sig: DataFrame, scratch: Scratch, chance: float, close: float) -> tuple[DataFrame, DataFrame]:
    """(a, b) of bucket centres and members that resemble them, and (bucket, rep) of the members not close to their centre."""
    centres = members.groupBy("bucket").agg(F.min("rep").alias("a"), F.count("*").alias("size")).where("size > 1")
    pairs = members.join(centres, "bucket").where("rep <> a").select("bucket", "a", F.col("rep").alias("b"))
    both = pairs.select("a", "b").distinct().join(sig.select(F.col("rep").alias("b"), F.col("sig").alias("sig_b")), "b").join(sig.select(F.col("rep").alias("a"), F.col("sig").alias("sig_a")), "a")

    def like(batches):
        for t in batches:
            x, y = (np.frombuffer(b"".join(t.column(c).to_pylist()), np.uint8).reshape(-1, BINS) for c in (2, 3))
            est = _likeness(x, y)
            yield pa.RecordBatch.from_arrays([t.column(0), t.column(1), pa.array(est >= chance), pa.array(est < close)], ["a", "b", "like", "far"])

    judged = scratch.write(both.select("a", "b", "sig_a", "sig_b").mapInArrow(like, "a long, b long, like boolean, far boolean"), "judged")
    return judged.where("like").select("a", "b"), pairs.join(judged.where("far").select("a", "b"), ["a", "b"]).select("bucket", F.col("b").alias("rep"))


def _likeness(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Estimated similarity of sketches of a byte per bin."""
    return ((x == y).mean(-1) - 1 / 256) * 256 / 255


def peeled(sig: np.ndarray, chance: float, close: float) -> list[tuple[int, int]]:
    """Spanning edges of a bucket: each member not close to an earlier centre is a centre for all that are left."""
    label, left, out = np.arange(len(sig)), np.arange(len(sig)), []
    while len(left) > 1:
        i, left = left[0], left[1:]
        est = _likeness(sig[i], sig[left])
        near = left[est >= chance]
        _, first = np.unique(label[near], return_index=True)
        for j in near[first]:
            if label[j] != label[i]:
                out.append((int(i), int(j)))
                label[label == label[j]] = label[i]
        left = left[est < close]
    return out


def _peel(chance: float, close: float):
    def run(group: pa.Table) -> pa.Table:
        g = group.sort_by([("bucket", "ascending"), ("x", "ascending"), ("y", "ascending"), ("rep", "ascending")])
        key = np.stack([g.column(c).to_numpy() for c in ("bucket", "x", "y")])
        rep, sig = g.column("rep").to_numpy(), np.frombuffer(b"".join(g.column("sig").to_pylist()), np.uint8).reshape(-1, BINS)
        cut = np.flatnonzero(np.concatenate(([True], (key[:, 1:] != key[:, :-1]).any(0), [True])))
        edges = np.array([(rep[lo + i], rep[lo + j]) for lo, hi in zip(cut, cut[1:], strict=False) for i, j in peeled(sig[lo:hi], chance, close)], np.int64).reshape(-1, 2)
        edges = np.unique(edges, axis=0)
        return pa.table({"a": pa.array(edges[:, 0], pa.int64()), "b": pa.array(edges[:, 1], pa.int64())})

    return run


def star_edges(reps: DataFrame, scratch: Scratch, chance: float = CHANCE, close: float = CLOSE) -> DataFrame:
    """(a, b): candidate edges that join any two documents of a bucket that are alike, directly or over a centre close to one of them."""
    sig = reps.select("rep", "sig")
    members, edges, few = reps.select("rep", F.explode("bands").alias("bucket")), [], []
    for step in range(STARS):
        found, left = _starred(members, sig, scratch, chance, close)
        edges.append(found)
        left = scratch.write(left, "left")
        sizes = scratch.write(left.groupBy("bucket").agg(F.count("*").alias("size")).where("size > 1"), "sizes")
        rest = left.join(sizes, "bucket")
        few.append(rest.where(F.col("size") <= LOCAL) if step < STARS - 1 else rest)
        if sizes.where(F.col("size") > LOCAL).isEmpty():
            break
        members = rest.where(F.col("size") > LOCAL).select("rep", "bucket")
    cells = functools.reduce(DataFrame.unionByName, few).withColumn("n", F.ceil(F.col("size") / LOCAL).cast("int")).withColumn("k", F.pmod(F.xxhash64("rep", F.lit(11)), F.col("n")).cast("int"))
    cells = cells.withColumn("o", F.explode(F.sequence(F.lit(0), F.col("n") - 1))).select("bucket", "rep", F.least("k", "o").alias("x"), F.greatest("k", "o").alias("y"))
    cells = scratch.write(cells, "cells")
    n = cells.count()
    if n:
        groups = max(default_parallelism(reps.sparkSession), n // 20_000)
        dealt = cells.join(sig, "rep").withColumn("cell", F.pmod(F.xxhash64("bucket", "x", "y"), F.lit(groups)))
        edges.append(dealt.groupBy("cell").applyInArrow(_peel(chance, close), "a long, b long"))
    return scratch.write(functools.reduce(DataFrame.unionByName, edges), "stars")


def linked(sets: list[np.ndarray], queries: int | None = None, percent: int = 80) -> list[tuple[int, int]]:
    """Spanning edges of the links among sets; with `queries`, only links with one of the first so many count."""
    n = len(sets)
    size = np.array([len(s) for s in sets], np.int64)
    value, column, count = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    row, often = np.repeat(np.arange(n), size), count > 1
    keep = often[column]
    row, column = row[keep], (np.cumsum(often) - 1)[column[keep]]
    m = n if queries is None else queries
    common = np.zeros((m, n), np.float32)
    order = np.argsort(column, kind="stable")
    row, column = row[order], column[order]
    width = max(256, 4_000_000 // n)
    for at in range(0, int(often.sum()), width):
        a, b = np.searchsorted(column, (at, at + width))
        x = np.zeros((n, width), np.float32)
        x[row[a:b], column[a:b] - at] = 1
        common += x[:m] @ x.T
    common = common.astype(np.int64)
    yes = 100 * common >= percent * (size[:m, None] + size[None, :] - common)
    root = list(range(n))

    def top(k: int) -> int:
        while root[k] != k:
            root[k] = root[root[k]]
            k = root[k]
        return k

    out = []
    for i, j in zip(*np.nonzero(yes), strict=True):
        a, b = top(int(i)), top(int(j))
        if a != b:
            root[max(a, b)] = min(a, b)
            out.append((int(i), int(j)))
    return out


def _settle(group: pa.Table) -> pa.Table:
    """Spanning links of each (cluster, block, chunk) of a group; role 1 rows are queries, 2 hubs."""
    g = group.sort_by([("cluster", "ascending"), ("block", "ascending"), ("chunk", "ascending"), ("role", "descending"), ("rep", "ascending")])
    key = np.stack([g.column(c).to_numpy() for c in ("cluster", "block", "chunk")])
    role, rep, blob = g.column("role").to_numpy(), g.column("rep").to_numpy(), g.column("hashes")
    cut = np.flatnonzero(np.concatenate(([True], (key[:, 1:] != key[:, :-1]).any(0), [True])))
    a, b = [], []
    for lo, hi in zip(cut, cut[1:], strict=False):
        ids, roles = rep[lo:hi], role[lo:hi]
        first = np.sort(np.unique(ids, return_index=True)[1])  # a query or hub also has its own row
        n_queries = int((roles[first] == 1).sum())
        if len(first) < 2 or (roles == 1).any() and not n_queries:
            continue
        sets = [np.frombuffer(blob[int(lo + k)].as_py(), np.uint64) for k in first]
        for i, j in linked(sets, n_queries or None):
            a.append(int(ids[first[i]]))
            b.append(int(ids[first[j]]))
    return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})


def settled(rows: DataFrame, groups: int) -> DataFrame:
    """Runs `_settle` over groups of whole (cluster, block, chunk) cells."""
    cells = rows.withColumn("cell", F.pmod(F.xxhash64("cluster", "block", "chunk"), F.lit(groups)))
    return cells.groupBy("cell").applyInArrow(_settle, "a long, b long")


def clustered(nodes: DataFrame, reps: DataFrame, scratch: Scratch, block: int) -> DataFrame:
    """(rep, cluster, set_key, n, blocks) of clustered representatives: blocks of bounded documents and shingles, known before any text is read."""
    rows = scratch.write(nodes.join(reps.select(F.col("rep").alias("node"), "set_key", "n"), "node").select(F.col("node").alias("rep"), F.col("component").alias("cluster"), "set_key", "n"), "wanted")
    blocks = F.greatest(F.ceil(F.count("*") / block), F.ceil(F.sum("n") / BLOCK_SHINGLES)).cast("int")
    return scratch.write(rows.join(scratch.write(rows.groupBy("cluster").agg(blocks.alias("blocks")), "blocks"), "cluster"), "wanted")


def member_bits(wanted: DataFrame, n: int) -> np.ndarray:
    """A Bloom filter of the wanted ids, two bits each: at most MEMBER_BITS, so what is sent never grows beyond that; a full one lets more through, and loses nothing."""
    size = 1 << min(MEMBER_BITS, max(16, (16 * n).bit_length()))
    h = F.xxhash64("rep")
    at = wanted.select(F.explode(F.array(*[x.bitwiseAND(F.lit(size - 1)) for x in (h, F.shiftrightunsigned(h, 32))])).alias("at"))
    words = at.groupBy(F.shiftright("at", 6).alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(at & 63 as int))")).alias("bits")).toArrow()
    out = np.zeros(size >> 6, np.uint64)
    out[words.column("word").to_numpy()] = words.column("bits").to_numpy().view(np.uint64)
    return out


def cluster_sets(docs: DataFrame, wanted: DataFrame, n: int, width: int, id_col: str, text: str) -> DataFrame:
    """(cluster, blocks, rep, hashes): the sets of clustered representatives, made anew from the texts.

    Texts stay where they lie: ids that cannot be wanted are passed over by a filter of fixed
    size, and only the sets of the others are exchanged.  The hint makes the join behave alike at
    every size; the ids of a large input are no broadcast.
    """
    sent = docs.sparkSession.sparkContext.broadcast(member_bits(wanted, n))
    schema = pa.schema([("rep", pa.int64()), ("set_key", pa.binary()), ("hashes", pa.binary())])

    def run(batches):
        bits = sent.value
        for batch in batches:
            h = batch.column(1).to_numpy().view(np.uint64)
            at = np.stack((h, h >> np.uint64(32))) & np.uint64(64 * len(bits) - 1)
            batch = batch.filter(pa.array((bits[at >> np.uint64(6)] >> (at & np.uint64(63)) & np.uint64(1)).all(0)))
            for ids, _, texts in slices([batch]):
                sets = [shingles(t, width) for t in texts]
                yield pa.RecordBatch.from_pydict({"rep": ids, "set_key": [xxhash.xxh3_128_digest(s.tobytes()) for s in sets], "hashes": [s.tobytes() for s in sets]}, schema=schema)

    ids = docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("rep"), F.xxhash64(F.col(id_col).cast("long")).alias("h"), F.col(text).alias("text"))
    sets = ids.mapInArrow(run, "rep long, set_key binary, hashes binary")
    return sets.join(wanted.select("rep", "set_key", "cluster", "blocks").hint("merge"), ["rep", "set_key"]).select("cluster", "blocks", "rep", "hashes")


def _hubs(wanted: DataFrame) -> DataFrame:
    """(cluster, rep): some members of each cluster of several blocks, drawn by hash in two steps so that no cluster meets in one task."""
    h = F.xxhash64("rep", F.lit(3))
    drawn = wanted.where("blocks > 1").select("cluster", "rep", h.alias("h"), F.pmod(h, F.lit(64)).alias("salt"))
    for keys in (["cluster", "salt"], ["cluster"]):
        drawn = drawn.withColumn("k", F.row_number().over(Window.partitionBy(*keys).orderBy("h", "rep"))).where(F.col("k") <= HUBS)
    return drawn.select("cluster", "rep")


def near_duplicates(docs: DataFrame, width: int = 4, id_col: str = "doc_id", text: str = "text", block: int = BLOCK) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept): the smallest id each document is linked with, over any number of links."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "neardup")
    sketched = scratch.write(sketches(docs, width, id_col, text), "sketches")
    first = F.min(F.struct("doc_id", "n", "sig", "bands")).alias("r")
    reps = scratch.write(sketched.where("n > 0 AND doc_id IS NOT NULL").groupBy("set_key").agg(first).select(F.col("r.doc_id").alias("rep"), "r.n", "set_key", "r.sig", "r.bands"), "sets")
    wanted = clustered(components(star_edges(reps, scratch), scratch), reps, scratch, block)
    total = wanted.agg(F.count("*").alias("n"), F.coalesce(F.sum("n"), F.lit(0)).alias("s"), F.coalesce(F.max("blocks"), F.lit(0)).alias("blocks")).first()
    groups = max(default_parallelism(spark), total["n"] // (2 * block), total["s"] // BLOCK_SHINGLES, 1)
    sets = scratch.write(cluster_sets(docs, wanted, total["n"], width, id_col, text), "members")
    cols = ["cluster", "block", "chunk", "role", "rep", "hashes"]
    everywhere = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    cut = sets.withColumn("block", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int")).withColumn("chunk", F.lit(0))
    rows = cut.withColumn("role", F.lit(0)).select(*cols)
    if total["blocks"] > 1:
        hubs = sets.join(_hubs(wanted), ["cluster", "rep"]).withColumn("block", everywhere).withColumn("chunk", F.lit(0)).withColumn("role", F.lit(2))
        rows = rows.unionByName(hubs.select(*cols))
    links = scratch.write(settled(rows, groups), "links")
    if total["blocks"] > 1:
        links = scratch.write(links.unionByName(_residual(cut, wanted, components(links, scratch), scratch, groups, cols)), "links")
    final = components(links, scratch).select(F.col("node").alias("rep"), "component")
    by_set = reps.select("rep", "set_key").join(final, "rep", "left").select("set_key", F.coalesce("component", "rep").alias("component_id"))
    out = sketched.select("doc_id", "n", "set_key").join(by_set, "set_key", "left")
    component = F.coalesce("component_id", "doc_id")
    return out.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def _residual(cut: DataFrame, wanted: DataFrame, comps: DataFrame, scratch: Scratch, groups: int, cols: list[str]) -> DataFrame:
    """Links of clusters of several blocks between their largest component and all the rest."""
    label = wanted.where("blocks > 1").select("cluster", "rep").join(comps.select(F.col("node").alias("rep"), "component"), "rep", "left")
    label = scratch.write(label.select("cluster", "rep", F.coalesce("component", "rep").alias("component")), "labels")
    sizes = label.groupBy("cluster", "component").agg(F.count("*").alias("size"))
    main = sizes.groupBy("cluster").agg(F.max(F.struct("size", "component")).alias("m"), F.count("*").alias("parts"), F.sum("size").alias("all")).where("parts > 1")
    main = main.select("cluster", F.col("m.component").alias("main"), F.ceil((F.col("all") - F.col("m.size")) / QUERIES).cast("int").alias("chunks"))
    open_ = scratch.write(main, "open")
    outside = label.join(open_, "cluster").where("component <> main").withColumn("chunk", F.pmod(F.xxhash64("rep", F.lit(7)), F.col("chunks")).cast("int")).select("cluster", "rep", "chunk")
    wide = cut.where("blocks > 1")
    queries = wide.drop("chunk", "block").join(outside, ["cluster", "rep"]).withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).withColumn("role", F.lit(1)).select(*cols)
    targets = wide.drop("chunk").join(open_.select("cluster", "chunks"), "cluster").withColumn("chunk", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1))).withColumn("role", F.lit(0)).select(*cols)
    return settled(queries.unionByName(targets), groups)
