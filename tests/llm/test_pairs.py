"""Near-duplicates, components, language model, fixity audit and the pipeline: against plain versions."""

from __future__ import annotations

import hashlib
import math
import random
from collections import Counter, defaultdict

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

import corpus_pipeline
from coreclust.llm import fixity, kneserney, minhash, pii
from coreclust.llm import queries as Q
from coreclust.llm.common import Scratch, table
from coreclust.llm.components import components

SF = "/root/testdata/sf0.001"


def lower(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")


def words(t):
    return [w for w in lower(t).encode().split() if w]


def rooted(n_or_ids, links):
    root = {i: i for i in n_or_ids}

    def top(k):
        while root[k] != k:
            root[k] = root[root[k]]
            k = root[k]
        return k

    for a, b in links:
        a, b = top(a), top(b)
        root[max(a, b)] = min(a, b)
    return {i: top(i) for i in root}


# ---------------------------------------------------------------- components


@pytest.mark.parametrize("seed", [0, 1])
def test_components_equal_union_find(spark, seed):
    rng = random.Random(seed)
    links = [(k, k + 1) for k in range(100, 160)] + [(rng.randrange(300), rng.randrange(300)) for _ in range(120)] + [(500, k) for k in range(501, 540)] + [(7, 7)]
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(links, "a long, b long"), Scratch(spark, "t")).collect()}
    want = rooted({x for e in links for x in e if e[0] != e[1]}, links)
    assert got == want


def test_no_edges(spark):
    assert components(spark.createDataFrame([], "a long, b long"), Scratch(spark, "t")).count() == 0


# ---------------------------------------------------------------- near-duplicates


def plain_sets(docs):
    out = {}
    for i, t in docs:
        w = words(t)
        out[i] = {tuple(w[k : k + 4]) for k in range(len(w) - 3)} or ({tuple(w)} if w else set())
    return out


def plain_groups(docs):
    s = plain_sets(docs)
    ids = sorted(s)
    links = [(a, b) for k, a in enumerate(ids) for b in ids[k + 1 :] if s[a] and s[b] and 100 * len(s[a] & s[b]) >= 80 * len(s[a] | s[b])]
    return {i: len(s[i]) for i in s}, rooted(ids, links)


def copies(seed, base_words, n, edits):
    """Copies of one text with up to `edits` words changed: many pairs lie on either side of the threshold."""
    rng = random.Random(seed)
    base = [f"b{seed}w{k}" for k in range(base_words)]
    out = []
    for c in range(n):
        w = list(base)
        for _ in range(rng.randrange(edits + 1)):
            w[rng.randrange(len(w))] = f"e{c}x{rng.randrange(10**6)}"
        out.append(" ".join(w))
    return out


def test_groups_equal_brute_force(spark):
    rng = random.Random(9)
    texts = copies(1, 120, 90, 9) + copies(2, 30, 40, 3) + copies(3, 6, 10, 1) + ["tiny text", "Tiny  TEXT", "tiny", "", None, "   "] * 2
    texts += [" ".join(f"r{rng.randrange(9999)}" for _ in range(rng.randrange(1, 90))) for _ in range(60)]
    rng.shuffle(texts)
    docs = list(enumerate(texts))
    n, want = plain_groups(docs)
    df = spark.createDataFrame(docs, "doc_id long, text string")
    for block in (256, 24):  # small blocks: several blocks and hubs to a cluster, and the residual step
        got = {r["doc_id"]: r for r in minhash.near_duplicates(df, block=block).collect()}
        assert {i: r["n_shingles"] for i, r in got.items()} == n
        assert {i: r["component_id"] for i, r in got.items()} == want
        assert all(r["kept"] == (i == r["component_id"]) for i, r in got.items())


def test_wanted_ids_pass_a_filter_of_any_size(spark, monkeypatch):
    """No wanted id is lost, most others are held back, and a full filter only lets more through."""
    docs = spark.range(6000).selectExpr("id as doc_id", "concat('w', id, ' a b c d') as text")
    wanted = minhash.sketches(docs.where("doc_id % 7 = 0")).selectExpr("doc_id as rep", "set_key", "1L as cluster", "1 as blocks")
    for bits in (26, 17, 6):
        monkeypatch.setattr(minhash, "MEMBER_BITS", bits)
        got = minhash.cluster_sets(docs, wanted, wanted.count(), 4, "doc_id", "text").select("rep").collect()
        assert sorted(r["rep"] for r in got) == list(range(0, 6000, 7))
    monkeypatch.setattr(minhash, "MEMBER_BITS", 26)
    assert np.bitwise_count(minhash.member_bits(wanted, wanted.count())).sum() <= 2 * wanted.count()


@given(st.lists(st.sets(st.integers(0, 12), min_size=1), min_size=2, max_size=12))
@settings(max_examples=100, deadline=None)
def test_links_of_a_block_span_the_same_groups(sets):
    arrays = [np.array(sorted(s), np.uint64) for s in sets]
    every = [(i, j) for i in range(len(sets)) for j in range(i) if 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j])]
    assert rooted(range(len(sets)), minhash.linked(arrays)) == rooted(range(len(sets)), every)
    few = [(i, j) for i, j in every if min(i, j) < 2]
    got = minhash.linked(arrays, 2)
    assert rooted(range(len(sets)), got) == rooted(range(len(sets)), few)


def test_densified_bins_estimate_similarity():
    rng = np.random.default_rng(4)
    k = minhash.Sketcher()
    for n in (3, 40, 400):
        est = []
        for _ in range(60):
            x = rng.integers(0, 2**63, n + max(1, n // 8), np.int64).astype(np.uint64)
            a, b = np.sort(x[:n]), np.sort(x[len(x) - n :])
            true = len(np.intersect1d(a, b)) / len(np.union1d(a, b))
            est.append((k.bins(a) == k.bins(b)).mean() - true)
        assert abs(np.mean(est)) < 0.08


def crowd(spark, n=600):
    """Pairs that share a bucket only behind `n` unlike documents with smaller ids, all unlike each other."""
    rng = np.random.default_rng(5)
    sig = rng.integers(0, 256, (n + 8, minhash.BINS)).astype(np.uint8)
    for k in range(n, n + 8, 2):
        sig[k + 1] = sig[k]
        sig[k + 1, : minhash.BINS // 5] += 1
    return spark.createDataFrame([(k, bytearray(s.tobytes()), [7]) for k, s in enumerate(sig)], "rep long, sig binary, bands array<long>"), [(k, k + 1) for k in range(n, n + 8, 2)]


@pytest.mark.parametrize("local", [minhash.LOCAL, 2000, 100])
def test_pairs_behind_unlike_centres_become_candidates(spark, monkeypatch, local):
    monkeypatch.setattr(minhash, "LOCAL", local)
    monkeypatch.setattr(minhash, "STARS", 2)
    reps, want = crowd(spark)
    got = {(r["a"], r["b"]) for r in minhash.star_edges(reps, Scratch(spark, "crowd")).collect()}
    assert got == set(want)


def test_near_duplicate_edges(odd, nothing):
    got = [(r["doc_id"], r["n_shingles"], r["component_id"], r["kept"]) for r in minhash.near_duplicates(odd).collect()]
    assert len(got) == odd.count() and (0, 0, 0, True) in got and got.count((4, 2, 4, True)) == 3
    assert all(kept for i, _, _, kept in got if i is None)
    assert minhash.near_duplicates(nothing).count() == 0


# ---------------------------------------------------------------- language model


def plain_model(train, order):
    """Counts, contexts and discounts by the definition, on lists of tokens with a start mark."""
    grams = {k: Counter() for k in range(1, order + 1)}
    for s in train:
        for i in range(1, len(s)):
            for k in range(1, order + 1):
                if i - k + 1 >= 0:
                    grams[k][tuple(s[i - k + 1 : i + 1])] += 1
    adjusted = {order: dict(grams[order])}
    for k in range(order - 1, 0, -1):
        a = Counter(g[1:] for g in grams[k + 1])
        adjusted[k] = {g: grams[k][g] if g[0] == "<s>" else a[g] for g in grams[k]}
    context = {k: defaultdict(lambda: [0, 0, 0, 0]) for k in range(2, order + 1)}
    for k in range(2, order + 1):
        for g, c in adjusted[k].items():
            x = context[k][g[:-1]]
            x[0] += c
            x[min(c, 3)] += 1
    discount = {}
    for k in adjusted:
        n = [sum(c == x for c in adjusted[k].values()) for x in (1, 2, 3, 4)]
        discount[k] = kneserney.Order([*n, 0, 0, 0, 0]).discounts()
    return grams[1], adjusted, context, discount


def plain_score(s, model, order):
    raw, adjusted, context, d = model
    v, mass = len(raw), sum(adjusted[1].values())
    free = sum(d[1][min(c, 3)] for c in adjusted[1].values()) / mass
    out = 0.0
    for i in range(1, len(s)):
        a = adjusted[1].get((s[i],), 0)
        p = (a - d[1][min(a, 3)]) / mass + free / (v + 1)
        for k in range(2, order + 1):
            h = tuple(s[i - k + 1 : i]) if i - k + 1 >= 0 else None
            if h and h in context[k]:
                t, *n = context[k][h]
                c = adjusted[k].get((*h, s[i]), 0)
                p = (c - d[k][min(c, 3)]) / t + sum(d[k][x + 1] * n[x] for x in range(3)) / t * p
        out += math.log10(p)
    return out


@pytest.mark.parametrize("order", [1, 2, 3])
def test_language_model_equals_its_definition(spark, order):
    rng = random.Random(order)
    docs = [(i, " ".join(rng.choice("abcdefgh") + rng.choice(["", "", "x"]) for _ in range(rng.randrange(30)))) for i in range(80)] + [(80, "unseen words Only"), (81, None), (82, "a b")]
    toks = {i: ["<s>", *[w.decode() for w in words(t)], "</s>"] for i, t in docs}
    train = [i for i in toks if i % 4]
    model = plain_model([toks[i] for i in train], order)
    df = spark.createDataFrame(docs, "doc_id long, text string")
    scores, kept = kneserney.run(df, F.col("doc_id") % 4 != 0, order, keep_model=True, block_tokens=150, shard_tokens=100)
    got = {r["doc_id"]: r for r in scores.collect()}
    raw, n, v = model[0], sum(model[0].values()), len(model[0])
    for i, s in toks.items():
        r = got[i]
        assert (r["n_tokens"], r["train_tokens"], r["n_known"]) == (len(s) - 1, n, sum((w,) in raw for w in s[1:]))
        assert r["base_score"] == pytest.approx(sum(math.log10((raw.get((w,), 0) + 1) / (n + v + 1)) for w in s[1:]))
        assert r["score"] == pytest.approx(plain_score(s, model, order))
    again = {r["doc_id"]: r["score"] for r in kneserney.score(df, kept, block_tokens=70).collect()}
    assert all(again[i] == pytest.approx(got[i]["score"]) for i in again) and len(again) == len(docs)


def test_probabilities_sum_to_one(spark):
    docs = [(0, "a b a c"), (1, "b a b"), (2, "c c a b")]
    toks = [["<s>", *t.split(), "</s>"] for _, t in docs]
    model = plain_model(toks, 2)
    for h in ("<s>", "a", "b"):
        total = sum(10 ** (plain_score(["<s>", h, w] if h != "<s>" else ["<s>", w], model, 2) - (plain_score(["<s>", h], model, 2) if h != "<s>" else 0)) for w in ("a", "b", "c", "</s>", "unseen"))
        assert total == pytest.approx(1)


def test_model_beats_the_base_on_held_out_text(spark):
    s = Q.op7_lm_scoring(spark, "/root/testdata/sf0.01").where("held_out")
    r = s.agg(kneserney.perplexity(s).alias("p"), kneserney.perplexity(s, "base_score").alias("b")).first()
    assert r["p"] < 0.5 * r["b"]


def test_language_model_edges(odd, nothing):
    scores, _ = kneserney.run(odd, F.lit(True))
    got = {r["doc_id"]: r for r in scores.collect()}
    assert scores.count() == odd.count() and got[0]["n_tokens"] == 1
    assert kneserney.run(nothing, F.lit(True))[0].count() == 0
    none = kneserney.run(odd, F.lit(False))[0].collect()
    assert all(r["train_tokens"] == 0 and r["score"] == 0 for r in none)


# ---------------------------------------------------------------- fixity


def test_audit_finds_planted_damage(spark):
    rows = [(i, f"http://h/{i}", "x" * (i % 7)) for i in range(600)] + [(600, None, None), (7, "http://h/7", "second"), (None, "u", "v")]
    left = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("digest", F.lit("clash"))
    right = left.where("page_id IS NULL OR page_id NOT IN (3, 411)").withColumn("html", F.when(F.coalesce(F.col("page_id").isin(0, 599), F.lit(False)), "changed").otherwise(F.col("html"))).unionByName(spark.createDataFrame([(9000, "u", "new", "clash")], left.schema))
    out = fixity.audit(left, right, Scratch(spark, "t")).collect()
    status = defaultdict(set)
    for r in out:
        status[r["status"]].add(r["page_id"])
    assert status["altered"] == {0, 599} and status["missing"] == {3, 411} and status["extra"] == {9000} and len(out) == len(rows) + 1
    one = next(r for r in out if r["page_id"] == 5)
    body = f"WARC/1.1\r\nWARC-Type: response\r\nWARC-Record-ID: <urn:page:5>\r\nWARC-Target-URI: http://h/5\r\nContent-Length: 5\r\n\r\nxxxxx\r\n\r\n"
    assert one["digest"] == hashlib.sha256(body.encode()).hexdigest() and one["length"] == len(body)
    file = sorted((r for r in out if r["segment"] == 0 and r["status"] != "extra"), key=lambda r: r["start"])
    assert all(a["start"] + a["length"] == b["start"] for a, b in zip(file, file[1:], strict=False))
    ranges = fixity.range_of(spark.createDataFrame([r for r in out if r["status"] != "ok"])).collect()
    assert sum(r["records"] for r in ranges) == 5


def test_equal_replicas_and_empty_ones(spark):
    pages = table(spark, SF, "pages")
    assert {r["status"] for r in fixity.audit(pages, pages, Scratch(spark, "t")).collect()} == {"ok"}
    assert fixity.roots(fixity.records(pages)).count() >= 1
    none = pages.where("page_id < 0")
    assert fixity.audit(none, none, Scratch(spark, "t")).count() == 0
    assert {r["status"] for r in fixity.audit(pages, none, Scratch(spark, "t")).collect()} == {"missing"}


# ---------------------------------------------------------------- pipeline


def test_pipeline_equals_its_stages_in_plain_python(spark):
    from tests.llm.test_texts import check_packing, plain_bootstrap, plain_contamination
    from tokenizers import Tokenizer

    from coreclust.llm.common import tokenizer_path

    docs = [r.asDict() for r in table(spark, SF, "documents").collect()]
    bench = [(r["item_id"], r["text"]) for r in table(spark, SF, "benchmark").collect()]
    left = [d for d in docs if d["text"] and any(c.isalpha() for c in d["text"])]
    _, group = plain_groups([(d["doc_id"], d["text"]) for d in left])
    left = [d for d in left if group[d["doc_id"]] == d["doc_id"]]
    bad = {i for i, *_, c in plain_contamination([(d["doc_id"], d["text"]) for d in left], bench) if c}
    left = [d for d in left if d["doc_id"] not in bad]

    def redacted(t, spans):
        out, at = "", 0
        for a, b, k in sorted((a, b, k) for k, a, b in spans):
            if b > at:
                out, at = (out + t[at:a] + f"<{pii.FOUND[k]}>" if a >= at else out), b
        return out + t[at:]

    want = sorted((d["doc_id"], redacted(d["text"], s)) for d, s in zip(left, plain_bootstrap([d["text"] for d in left]), strict=True))
    frame = table(spark, SF, "documents")
    columns, scratch = frame.columns, Scratch(spark, "t")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        frame = scratch.write(stage(spark, frame, SF), name)
        assert frame.columns == columns
    got = frame.orderBy("doc_id").collect()
    assert [(r["doc_id"], r["text"]) for r in got] == want and all(r["n_chars"] == len(r["text"]) for r in got)
    out = corpus_pipeline.run(spark, SF).collect()
    check_packing(out, want, Tokenizer.from_file(tokenizer_path("byte_bpe_50k.json")))


def test_pipeline_stages_take_odd_and_empty_tables(spark, odd, nothing):
    cols = ["doc_id", "text", "lang", "source", "n_chars"]
    for docs in (odd, nothing):
        frame = docs.select(*cols)
        for _, stage in corpus_pipeline.STAGES:
            frame = Scratch(spark, "t").write(stage(spark, frame, SF), "x")
        assert frame.count() == 0 if docs is nothing else frame.count() > 0


def test_every_operator_is_registered():
    names = [k for k in Q.QUERIES if k.startswith("op")]
    assert sorted(int(k[2:].split("_")[0]) for k in names) == list(range(1, 11)) and set(Q.ORACLE_SQL) <= set(names)
