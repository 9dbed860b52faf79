"""Quality classifier from weak labels.

Overlapping heuristic labellers vote good, bad or abstain on every document.  Votes are
counted per pattern, so expectation-maximisation of the labellers' accuracies runs on a table
whose size depends on the number of labellers only.  Posterior labels of a bounded sample then
train a linear scorer on hashed features, which scores every document.

Labellers are not independent given good or bad: each knows one fault, and passes text with
another.  So bad text is of one of as many kinds as there are labellers, kind k being what
labeller k is for, and votes are independent given the kind.  What a labeller is for enters as
pseudo-counts in proportion to the corpus (`ANCHOR` for votes on good text and of a kind's own
labeller, `LOOSE` for the rest), so that a fit does not depend on size; no accuracy is bounded.

The sample bound (`SAMPLE`) is a parameter; votes, pattern counts and scores cover all rows.

Edge cases.  Null text counts as empty.  A document on which every labeller abstains has the
prior as its posterior.  Without rows the result is empty.  Repeated rows count and are scored
each.  Texts are read whole.
"""

from __future__ import annotations

import json
from zlib import crc32

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import LOWER, encode, map_rows
from .rules import MEASURES, measure_one

GOOD, BAD, ABSTAIN = 2, 1, 0
#: Documents that train the scorer, at most.
SAMPLE = 8_192
#: Weight of the prior votes as a share of all documents: of good text and of a kind's own labeller, and of all others.
ANCHOR, LOOSE = 2.0, 0.01
#: Prior chances to abstain, blame and pass: on good text, of a kind's own labeller, of the others; and the prior share of good text.
ON_GOOD, ON_OWN, ON_OTHER, GOOD_SHARE = (0.3, 0.001, 0.699), (0.15, 0.8, 0.05), (0.3, 0.15, 0.55), 0.8
#: Mean of posterior and score from which a document is kept.
KEEP = 0.5
#: Hashed feature space; its weights are what travels to the tasks.
DIMENSIONS = 1 << 16
SHAPE = bytes(97 if 97 <= LOWER[c] <= 122 and c > 96 else 65 if 65 <= c <= 90 else 57 if 48 <= c <= 57 else 120 if c >= 128 else c for c in range(256))


def labellers() -> dict[str, Column]:
    """Name to vote; thresholds leave a gap between good and bad in which a labeller abstains."""
    c, per_word = F.col, lambda x: F.col(x) / F.greatest(F.col("n_words"), F.lit(1))
    vote = lambda bad, good: F.when(bad, BAD).when(good, GOOD).otherwise(ABSTAIN)
    share = lambda x, y: F.col(x) / F.greatest(F.col(y), F.lit(1))
    return {
        "symbols": vote(per_word("n_symbols") > 0.15, per_word("n_symbols") < 0.02),
        "capitals": vote(share("n_upper", "n_letters") > 0.4, share("n_upper", "n_letters") < 0.15),
        "repeats": vote(per_word("n_repeat_words") > 0.2, per_word("n_repeat_words") < 0.02),
        "stutter": vote(per_word("n_same_next") > 0.1, per_word("n_same_next") < 0.03),
        "lines": vote(share("n_dup_lines", "n_lines") > 0.4, share("n_dup_lines", "n_lines") < 0.2),
        "word_length": vote((per_word("word_chars") < 2) | (per_word("word_chars") > 30), per_word("word_chars").between(3, 12)),
        "shouts": vote(per_word("n_shouts") > 0.2, per_word("n_shouts") < 0.02),
        "distinct": vote((share("n_distinct", "n_words") < 0.15) & (c("n_words") < 2000), (share("n_distinct", "n_words") > 0.3) & (c("n_words") >= 20)),
    }


def _features(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Hashed features and weights of one document: words, the shapes of their ends, and repeats of the word before."""
    shapes = b" ".join(words).translate(SHAPE).split()
    keys = [crc32(w) for w in words] + [crc32(s[-3:], 1) for s in shapes] + [crc32(s[:1] + s[-1:], 2) for s in shapes]
    same = sum(a == b for a, b in zip(words, words[1:], strict=False))
    at, n = np.unique(np.array(keys, np.uint32) % DIMENSIONS, return_counts=True)
    w = n / max(1, len(words))
    if same:
        at, w = np.append(at, DIMENSIONS), np.append(w, same / len(words))
    return at.astype(np.uint32), np.sqrt(w).astype(np.float32)


VOTED = MEASURES + ", n_shouts long, n_distinct long"


def _voted_one(t: str | None) -> tuple[int, ...]:
    words = encode(t).split()
    return (*measure_one(t), sum(w.endswith(b"!!") for w in words), len(set(words)))


def _pattern() -> Column:
    code = F.lit(0)
    for k, v in enumerate(labellers().values()):
        code = code + v * 3**k
    return code.cast("int").alias("pattern")


def votes(docs: DataFrame, id_col: str = "doc_id", text: str = "text", features: bool = False) -> DataFrame:
    """(doc_id, pattern): the labellers' votes as one base-3 number; with `features`, also the hashed features."""
    schema = VOTED + ", at binary, value binary"
    names = [x.split()[0] for x in VOTED.split(", ")][1:]

    def make():
        def f(ids, texts):
            out = {"doc_id": ids} | dict(zip(names, zip(*map(_voted_one, texts), strict=True), strict=True))
            made = [_features(encode(t).split()) if features else None for t in texts]
            return out | {"at": [m and m[0].tobytes() for m in made], "value": [m and m[1].tobytes() for m in made]}

        return f

    measured = map_rows(docs.select(F.col(id_col).alias("doc_id"), F.col(text).alias("text")), make, schema)
    return measured.select("doc_id", _pattern(), *["at", "value"] * features)


class LabelModel:
    """Accuracies of labellers with abstention on good text and on each kind of fault, by expectation-maximisation on pattern counts.

    `vote[k, c, x]` is labeller k's chance of vote x on class c, class 0 being good text and
    class 1 + j fault j; `share` are the classes' shares.
    """

    def __init__(self, counts: dict[int, int], n_labellers: int, rounds: int = 300):
        patterns = np.array(sorted(counts), np.int64)
        n = np.array([counts[int(p)] for p in patterns], float)
        v = np.stack([patterns // 3**k % 3 for k in range(n_labellers)], 1) if len(patterns) else np.zeros((0, n_labellers), np.int64)
        own = np.arange(n_labellers)
        prior, weight = np.tile(np.array(ON_OTHER), (n_labellers, 1 + n_labellers, 1)), np.full((n_labellers, 1 + n_labellers), LOOSE)
        prior[:, 0], prior[own, 1 + own] = ON_GOOD, ON_OWN
        weight[:, 0] = weight[own, 1 + own] = ANCHOR
        self.share = np.array([GOOD_SHARE, *[(1 - GOOD_SHARE) / n_labellers] * n_labellers])
        self.vote = prior.copy()
        pseudo = prior * weight[:, :, None] * n.sum()
        for _ in range(rounds if len(patterns) else 0):
            mass, before = self._classes(v) * n[:, None], self.vote
            self.vote = pseudo + np.stack([(v == x).T @ mass for x in range(3)], 2)
            self.vote /= self.vote.sum(2, keepdims=True)
            self.share = (mass.sum(0) + 1e-3) / (n.sum() + 1e-3 * len(self.share))
            if np.abs(before - self.vote).max() < 1e-8:
                break
        self.posterior = dict(zip(patterns.tolist(), self._classes(v)[:, 0].tolist(), strict=True))

    def _classes(self, v: np.ndarray) -> np.ndarray:
        """Chances of the classes given the votes."""
        score = np.log(self.vote[np.arange(v.shape[1])[None], :, v]).sum(1) + np.log(self.share)
        chance = np.exp(score - score.max(1, keepdims=True))
        return chance / chance.sum(1, keepdims=True)

    def accuracies(self) -> np.ndarray:
        """Per labeller, the chance that a vote that is no abstention is right."""
        given = self.vote * self.share[None, :, None]
        return (given[:, 0, GOOD] + given[:, 1:, BAD].sum(1)) / given[:, :, 1:].sum((1, 2))


def train_scorer(rows: list[tuple[np.ndarray, np.ndarray, float]], epochs: int = 12, rate: float = 2.0, decay: float = 1e-5) -> np.ndarray:
    """Logistic weights from (features, values, posterior) rows, by adaptive gradient steps on mini-batches; the last entry is the intercept."""
    w, seen = np.zeros(DIMENSIONS + 2, np.float64), np.full(DIMENSIONS + 2, 1e-3)
    rng = np.random.default_rng(0)
    for _ in range(epochs):
        order = rng.permutation(len(rows))
        for at in range(0, len(rows), 64):
            part = [rows[i] for i in order[at : at + 64]]
            col = np.concatenate([np.append(r[0], DIMENSIONS + 1) for r in part]).astype(np.int64)
            val = np.concatenate([np.append(r[1], 1) for r in part])
            row = np.repeat(np.arange(len(part)), [len(r[0]) + 1 for r in part])
            z = np.bincount(row, w[col] * val, len(part))
            error = 1 / (1 + np.exp(-np.clip(z, -30, 30))) - np.array([r[2] for r in part])
            col, where = np.unique(col, return_inverse=True)
            g = np.bincount(where, error[row] * val) / len(part) + decay * w[col]
            seen[col] += g * g
            w[col] -= rate * 0.1 * g / np.sqrt(seen[col])
    return w.astype(np.float32)


def classify(docs: DataFrame, id_col: str = "doc_id", text: str = "text", sample: int = SAMPLE) -> DataFrame:
    """(doc_id, posterior, score, kept) of every document: the label model's and the scorer's chance of good quality."""
    counts = {r["pattern"]: r["n"] for r in votes(docs, id_col, text).groupBy("pattern").agg(F.count("*").alias("n")).collect()}  # at most 3 to the number of labellers rows
    model = LabelModel(counts, len(labellers()))
    total = max(1, sum(counts.values()))
    share = int(min(1.0, 0.97 * sample / total) * (1 << 30))
    drawn = docs.where(F.pmod(F.xxhash64(id_col, F.lit(11)), F.lit(1 << 30)) < share).limit(sample)
    train = [(np.frombuffer(r["at"], np.uint32), np.frombuffer(r["value"], np.float32), model.posterior[r["pattern"]]) for r in votes(drawn, id_col, text, features=True).toLocalIterator()]
    weights = train_scorer(train)
    posterior = model.posterior
    columns = [x.split()[0] for x in VOTED.split(", ")][1:]

    def make():
        def f(ids, texts):
            out = {"doc_id": ids} | dict(zip(columns, zip(*map(_voted_one, texts), strict=True), strict=True))
            z = []
            for t in texts:
                at, value = _features(encode(t).split())
                z.append(float(weights[at] @ value + weights[-1]))
            return out | {"score": (1 / (1 + np.exp(-np.clip(z, -30, 30)))).tolist()}

        return f

    scored = map_rows(docs.select(F.col(id_col).alias("doc_id"), F.col(text).alias("text")), make, VOTED + ", score double").select("doc_id", _pattern(), "score")
    table = F.from_json(F.lit(json.dumps({str(k): v for k, v in posterior.items()})), "map<string,double>")
    scored = scored.select("doc_id", F.element_at(table, F.col("pattern").cast("string")).alias("posterior"), "score")
    return scored.select("doc_id", "posterior", "score", ((F.col("score") + F.col("posterior")) / 2 >= KEEP).alias("kept"))
