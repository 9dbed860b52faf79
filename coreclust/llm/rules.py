"""Quality rules as a bitmask ledger.

Every rule is evaluated once per document.  The ledger keeps the measurements and one integer
of failure bits.  A policy is a named, versioned mask: applying it, comparing two versions, or
asking what one rule alone removes (an ablation) reads only the bits.

Edge cases.  Null text counts as empty: no words, which fails `few_words`.  Lines without a
word are never duplicates.  Repeated rows get a row each.  Texts are read whole.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import encode, map_rows

SPACES = b" \t\n\x0b\f\r"
SYMBOLS = b"#*$%&|<>"
UPPER, LETTERS = bytes(range(65, 91)), bytes([*range(65, 91), *range(97, 123)])
MEASURES = "doc_id long, n_words long, word_chars long, n_symbols long, n_lines long, n_dup_lines long, n_repeat_words long, n_upper long, n_letters long, n_same_next long"


def repeated_words(ids: np.ndarray, width: int = 5) -> int:
    """Words that lie in a window of `width` words that the text has at least twice."""
    n = len(ids) - width + 1
    if n < 2:
        return 0
    key = ids[:n].astype(np.uint64)
    for k in range(1, width):
        key = key * np.uint64(0x9E3779B97F4A7C15) + ids[k : k + n].astype(np.uint64) + np.uint64(k)
        key ^= key >> np.uint64(31)
    if len(np.unique(key)) == n:
        return 0  # equal windows have equal keys
    key, have = ids[:n].astype(np.int64), 1  # exact: windows are renumbered after each added word
    base = int(ids.max()) + 1
    while have < width:
        key = np.unique(key * base + ids[have : have + n], return_inverse=True)[1].astype(np.int64)
        have += 1
    twice = np.flatnonzero(np.bincount(key)[key] > 1)
    hit = np.zeros(len(ids) + 1, np.int64)
    np.add.at(hit, twice, 1)
    np.add.at(hit, twice + width, -1)
    return int((np.cumsum(hit)[:-1] > 0).sum())


def measure_one(text: str | None) -> tuple[int, ...]:
    raw = encode(text)
    words = raw.split()
    number: dict[bytes, int] = {}
    ids = np.fromiter((number.setdefault(w, len(number)) for w in words), np.int64, len(words))
    lines = [x for x in raw.split(b"\n") if x.strip(SPACES)]
    count = lambda drop: len(raw) - len(raw.translate(None, drop))
    return (len(words), len(text or "") - count(SPACES), count(SYMBOLS), len(lines), len(lines) - len(set(lines)), repeated_words(ids), count(UPPER), count(LETTERS), int((ids[1:] == ids[:-1]).sum()))


def measure(docs: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """One row of integer measurements per document."""
    names = [x.split()[0] for x in MEASURES.split(", ")][1:]

    def make():
        def f(ids, texts):
            return {"doc_id": ids} | dict(zip(names, zip(*map(measure_one, texts), strict=True), strict=True))

        return f

    return map_rows(docs.select(F.col(id_col).alias("doc_id"), F.col(text).alias("text")), make, MEASURES)




#: Rule name to its failure condition over the measurements, in bit order; new rules go at the end so that stored bits keep their meaning.
RULES = {
    "few_words": "n_words < 10",
    "repeated_windows": "100 * n_repeat_words > 20 * n_words",
    "symbols": "5 * n_symbols > n_words",
    "duplicate_lines": "10 * n_dup_lines > 3 * n_lines",
    "short_words": "word_chars < 2 * n_words",
    "long_words": "word_chars > 50 * n_words",
    "shouting": "2 * n_upper > n_letters",
    "stutter": "10 * n_same_next > n_words",
}


#: Policy version to the rules it enforces.
POLICIES = {
    "base": ("few_words", "repeated_windows"),
    "v1": ("few_words", "repeated_windows", "symbols", "duplicate_lines"),
    "v2": ("few_words", "repeated_windows", "symbols", "duplicate_lines", "short_words", "long_words", "shouting", "stutter"),
}


def mask(policy: str | tuple[str, ...]) -> int:
    names = list(RULES)
    return sum(1 << names.index(r) for r in (POLICIES[policy] if isinstance(policy, str) else policy))


def ledger(measured: DataFrame) -> DataFrame:
    """The measurements and `failed`: bit i is set when rule i fails."""
    bits = [F.when(F.expr(x), F.lit(1 << i)).otherwise(F.lit(0)).cast("long") for i, x in enumerate(RULES.values())]
    total = bits[0]
    for b in bits[1:]:
        total = total.bitwiseOR(b)
    return measured.withColumn("failed", total)


def apply_policy(book: DataFrame, policy: str | tuple[str, ...], name: str = "kept") -> DataFrame:
    return book.withColumn(name, F.col("failed").bitwiseAND(F.lit(mask(policy))) == 0)


def ablations(book: DataFrame, policy: str) -> DataFrame:
    """Per rule of the policy: documents that fail it, that fail only it, and that any rule removes.

    The ledger is reduced to counts per bit pattern (at most two to the number of rules) before anything else.
    """
    m = mask(policy)
    patterns = book.select(F.col("failed").bitwiseAND(F.lit(m)).alias("bits")).groupBy("bits").agg(F.count("*").alias("n"))
    names = [(i, r) for i, r in enumerate(RULES) if m >> i & 1]
    each = patterns.select("bits", "n", F.explode(F.array(*[F.struct(F.lit(r).alias("rule"), F.lit(1 << i).cast("long").alias("bit")) for i, r in names])).alias("r"))
    total = F.sum(F.when(F.col("bits") != 0, F.col("n")).otherwise(0))
    return each.groupBy("r.rule").agg(
        F.sum(F.when(F.col("bits").bitwiseAND(F.col("r.bit")) != 0, F.col("n")).otherwise(0)).alias("n_failed"),
        F.sum(F.when(F.col("bits") == F.col("r.bit"), F.col("n")).otherwise(0)).alias("n_only_here"),
        total.alias("n_removed"),
    )


def contradictions(book: DataFrame, old: str, new: str) -> DataFrame:
    """Documents on which two policy versions disagree."""
    return apply_policy(apply_policy(book, old, "kept_old"), new, "kept_new").where(F.col("kept_old") != F.col("kept_new")).select("doc_id", "kept_old", "kept_new")
