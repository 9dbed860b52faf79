"""Language identification by rank-order profiles.

A profile is the list of a language's most frequent 1- to 3-character grams, most frequent
first.  A document's own list is compared with every profile by out-of-place distance: a gram
costs the difference of its two ranks, and the full list length when the profile lacks it.

Edge cases.  Null text, or text without a letter: language `und`, score 0.  Ties between
grams go to the smaller code, ties between languages to the smaller name.  No labelled row at
all: every prediction is `und`.  Repeated rows count and are answered once each.  Texts of any
length are read whole.
"""

from __future__ import annotations

import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import SLICE, extend_rows, map_rows

#: Length of a profile.
TOP = 300
#: Languages a model may have; their profiles travel to every task, so the size is checked.
MAX_LANGUAGES = 5_000
#: Distinct grams a training task holds before it hands them on.
HELD = 2_000_000
NONE = 0x1FFFFF
_LETTERS: np.ndarray | None = None


def _letters() -> np.ndarray:
    """For each code point: 2 a letter, 1 a mark that belongs to a word, 0 anything else."""
    global _LETTERS
    if _LETTERS is None:
        kinds = {"L": 2, "M": 1}
        _LETTERS = np.fromiter((kinds.get(unicodedata.category(chr(c))[0], 0) for c in range(0x110000)), np.uint8, 0x110000)
    return _LETTERS


def _codes(text: str | None) -> np.ndarray | None:
    """Lower-case word characters, words parted by one 32 and two at the end; None without a letter."""
    if not text:
        return None
    x = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
    kind = _letters()[x]
    if not (kind == 2).any():
        return None
    x = np.concatenate(([32], np.where(kind > 0, x, 32), [32]))
    x = x[np.concatenate(([True], (x[1:] != 32) | (x[:-1] != 32)))]
    return np.concatenate((x, [32]))


def gram_counts(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Keys and counts of the 1- to 3-grams of one or more strings from `_codes`, from one sort."""
    tri, n3 = np.unique((x[:-2] << 42) | (x[1:-1] << 21) | x[2:], return_counts=True)
    first = tri >> 21
    at = np.flatnonzero(np.concatenate(([True], first[1:] != first[:-1])))
    two, n2 = first[at], np.add.reduceat(n3, at)
    head = two >> 21
    at1 = np.flatnonzero(np.concatenate(([True], head[1:] != head[:-1])))
    one, n1 = head[at1], np.add.reduceat(n2, at1)
    gap = 32 << 21 | 32
    keep3, keep2, keep1 = ((tri & (2**42 - 1)) != gap) & (first != gap), two != gap, one != 32
    keys = np.concatenate((one[keep1] << 42 | NONE << 21 | NONE, two[keep2] << 21 | NONE, tri[keep3]))
    return keys, np.concatenate((n1[keep1], n2[keep2], n3[keep3]))


def ranked(keys: np.ndarray, counts: np.ndarray, top: int) -> np.ndarray:
    """The `top` most frequent keys, in order; ties to the smaller key."""
    if len(keys) > top:
        least = np.partition(counts, len(counts) - top)[len(counts) - top]
        keep = counts >= least
        keys, counts = keys[keep], counts[keep]
    return keys[np.lexsort((keys, -counts))[:top]]


def fit(docs: DataFrame, text: str = "text", lang: str = "lang", top: int = TOP) -> DataFrame:
    """Profiles (lang, rank, gram) from every labelled row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, tuple[np.ndarray, np.ndarray]] = {}

        def out():
            for name, (k, n) in held.items():
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(k), pa.string()), pa.array(k, pa.int64()), pa.array(n, pa.int64())], ["lang", "gram", "n"])
            held.clear()

        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                by: dict[str, list[np.ndarray]] = {}
                for t, name in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    if (x := _codes(t)) is not None:
                        by.setdefault(name, []).append(x)
                for name, xs in by.items():
                    k, n = gram_counts(np.concatenate(xs))
                    if name in held:
                        k, where = np.unique(np.concatenate((held[name][0], k)), return_inverse=True)
                        n = np.bincount(where, np.concatenate((held[name][1], n))).astype(np.int64)
                    held[name] = k, n
                if sum(len(k) for k, _ in held.values()) > HELD:
                    yield from out()
        yield from out()

    rows = docs.where(F.col(lang).isNotNull() & F.col(text).isNotNull()).select(F.col(text).alias("text"), F.col(lang).cast("string").alias("lang"))
    counts = rows.mapInArrow(run, "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    order = Window.partitionBy("lang").orderBy(F.desc("n"), F.asc("gram"))
    return counts.withColumn("rank", F.row_number().over(order) - 1).where(F.col("rank") < top).select("lang", "rank", "gram")


def profile_matrix(profiles: DataFrame, top: int = TOP) -> tuple[list[str], np.ndarray, np.ndarray]:
    """Languages, sorted grams, and each language's rank of each gram (`top` where it lacks it)."""
    rows = profiles.limit(MAX_LANGUAGES * top + 1).toArrow().to_pydict()
    langs = sorted(set(rows["lang"]))
    if len(langs) > MAX_LANGUAGES or len(rows["lang"]) > MAX_LANGUAGES * top:
        raise ValueError(f"more than {MAX_LANGUAGES} languages")
    grams = np.unique(np.array(rows["gram"], np.int64))
    ranks = np.full((len(langs), len(grams)), top, np.int32)
    where = {x: i for i, x in enumerate(langs)}
    if langs:
        ranks[[where[x] for x in rows["lang"]], np.searchsorted(grams, np.array(rows["gram"], np.int64))] = rows["rank"]
    return langs, grams, ranks


def _predictor(profiles: DataFrame, top: int):
    langs, grams, ranks = profile_matrix(profiles, top)

    def one(t: str | None) -> tuple[str, float]:
        x = _codes(t) if langs else None
        if x is None:
            return "und", 0.0
        keys = ranked(*gram_counts(x), top)
        at = np.minimum(np.searchsorted(grams, keys), len(grams) - 1)
        known = grams[at] == keys
        r = ranks[:, at]
        cost = np.where(known & (r < top), np.abs(r - np.arange(len(keys))), top).sum(1)
        best = int(cost.argmin())
        return langs[best], float(1 - cost[best] / (top * len(keys)))

    return one


def identify(docs: DataFrame, profiles: DataFrame, id_col: str = "doc_id", text: str = "text", top: int = TOP) -> DataFrame:
    """(doc_id, lang_pred, score): the nearest profile; score 1 is a perfect match of ranks, 0 nothing in common."""
    one = _predictor(profiles, top)

    def make():
        def f(ids, texts):
            got = [one(t) for t in texts]
            return {"doc_id": ids, "lang_pred": [g[0] for g in got], "score": [g[1] for g in got]}

        return f

    return map_rows(docs.select(F.col(id_col).alias("doc_id"), F.col(text).alias("text")), make, "doc_id long, lang_pred string, score double")


def annotated(docs: DataFrame, profiles: DataFrame, text: str = "text", top: int = TOP) -> DataFrame:
    """`docs` with `lang_pred` and `lang_score` added; columns of these names are replaced."""
    one = _predictor(profiles, top)
    docs = docs.drop("lang_pred", "lang_score")

    def make():
        def f(texts):
            got = [one(t) for t in texts]
            return {"lang_pred": [g[0] for g in got], "lang_score": [g[1] for g in got]}

        return f

    return extend_rows(docs, [text], make, "lang_pred string, lang_score double")


def recognised(docs: DataFrame, profiles: DataFrame, least: float, text: str = "text", top: int = TOP) -> DataFrame:
    """The rows and columns of `docs` whose text has letters and scores at least `least` with its nearest profile."""
    one = _predictor(profiles, top)
    where = docs.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, SLICE):
                part = batch.slice(at, SLICE)
                got = [one(t) for t in part.column(where).to_pylist()]
                yield part.filter(pa.array([lang != "und" and score >= least for lang, score in got], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
