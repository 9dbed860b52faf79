"""Personal data: shape matches, widened by bootstrapped contextual extraction.

Shapes (e-mail, IP address, payment card, phone) give the base spans and the seed entities; long
mixed keys are seeds of a fifth kind, `secret`, whose shape alone is never enough for a span.
The tokens around an entity are its lexical patterns: the token before it, the two before it, and
the one before with the one after.  Tokens with a digit or an @ are one class, `#`.  Patterns and
the identifier-like tokens in their slots form a graph; Spark scores it in rounds: a pattern is
as sure as the share of its instances that are known, weighed by how often the pattern holds an
identifier at all, and an instance is as sure as its patterns together; it counts for patterns
once it is sure itself.  Patterns that end up sure, with several different seeds, mark
identifiers which no shape matched, the most telling pattern first.

Everything runs on DataFrame functions.  Positions are code points, ends exclusive.

Edge cases.  Null text counts as empty: no spans.  Repeated rows are answered each but count
once as a seed value.  Without seeds or repeated contexts nothing is added.  Shapes are
possessive and start only where a run starts, so long runs cost linear time.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch

KINDS = ("email", "ip", "card", "phone")
#: Kinds that only contexts give follow the base kinds.
FOUND = (*KINDS, "secret")
#: Same matches as the plain shapes: a run is entered at its start (or right after a match), and never given back.
SHAPES = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
OCTETS = r"^0*(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])(?:\.0*(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])){3}$"
#: Characters between words, and between tokens that could be identifiers; single ones, as ranges make slow classes.
SPACE = r"\t\n\x0B\f\r\x20\x22\x27()"
EDGE = SPACE + ",;:="
DIGITS = "0123456789"
#: A token that could be an identifier: at least three digits in it, or an address sign; its span ends before trailing marks.
CANDIDATE = rf"(?<![^{EDGE}])(?:[^{EDGE}{DIGITS}]*+(?:[{DIGITS}][^{EDGE}{DIGITS}]*+){{3,}}+|[^{EDGE}]*?(?:@|\[at\])[^{EDGE}]++)"
TRAILING = ".!?*#$%&|<>-_/"
#: A key: long, of letters and digits.
SECRET = (r"^[A-Za-z0-9_-]{32,}$", "[0-9]", "[A-Za-z]")
#: Different seed values, and share of known instances times share of all its places, that a pattern needs; an instance counts from the latter on.
SEEDS, SURE = 3, 0.5
#: Supported patterns up to which their places are looked up by a broadcast; beyond, places are counted first and then joined.
SENT = 50_000
#: Entries of a running sum that are made at a time.
CHUNK = 256
ROUNDS = 3
SPAN = "struct<kind:int,start:int,end:int>"


MATCHES = "array<struct<start:int,end:int,value:string,patterns:array<bigint>>>"
#: Conditions on a match `m` of each base kind, and on a free token `v` that is a key.
DIGITS_OF = "length(regexp_replace(m.value, '[^0-9]', ''))"
VALID = {
    "email": "true",
    "ip": f"m.value rlike r'{OCTETS}'",
    "card": f"{DIGITS_OF} between 13 and 19 and luhn_check(regexp_replace(m.value, '[^0-9]', ''))",
    "phone": f"{DIGITS_OF} between 9 and 15",
}
#: What a text must hold for a kind: a cheap test that spares most texts the search.
MAY = {"email": "contains(text, '@')", "ip": r"text rlike r'[0-9]\.[0-9]'", "card": r"text rlike r'[0-9](?:[\x20-]?[0-9]){12}'", "phone": r"text rlike r'\+[0-9]'"}
IS_SECRET = " and ".join(f"v rlike r'{x}'" for x in SECRET)


def words(text: str) -> str:
    """SQL of the lower-case words of a text, those with a digit or an @ as `#`."""
    classed = rf"regexp_replace(lower({text}), r'(?<![^{SPACE}])[^{SPACE}{DIGITS}@]*+[{DIGITS}@][^{SPACE}]*+', '#')"
    return f"filter(split(if({text} rlike '[0-9@]', {classed}, lower({text})), r'[{SPACE}]+'), t -> t <> '')"


def keys(a: str, b: str, c: str) -> str:
    """SQL of the hashes of the patterns `a _ c`, `a b` and `a` of three words in a row; null where a word is missing."""
    return f"array(if({c} is null, null, xxhash64(3, {a}, {c})), if({b} is null, null, xxhash64(2, {a}, {b})), xxhash64(1, {a}))"


def patterns(before: str, after: str, first: str) -> str:
    """SQL of a match's patterns [around, two, one], from the words before it, since the match before (none for the `first`), and after it."""
    last = "w.l[size(w.l) - 1]"
    two = f"if(size(w.l) > 1, xxhash64(2, w.l[size(w.l) - 2], {last}), if({first}, null, xxhash64(2, '#', {last})))"
    around = f"if(size(w.r) > 0, xxhash64(3, {last}, w.r[0]), null)"
    return f"transform(array(struct({words(before)} as l, {words(after)} as r)), w -> if(size(w.l) > 0, array({around}, {two}, xxhash64(1, {last})), cast(array() as array<bigint>)))[0]"


def running(lengths: str) -> str:
    """SQL of the running sums of an array, in chunks, as a sum that grows by one entry at a time copies all before it."""
    last = "if(size({0}) = 0, 0, {0}[size({0}) - 1])"
    summed = lambda x: f"aggregate({x}, cast(array() as array<int>), (acc, y) -> concat(acc, array({last.format('acc')} + y)))"
    parts = f"transform(transform(sequence(0, cast((size(a) - 1) div {CHUNK} as int)), k -> slice(a, k * {CHUNK} + 1, {CHUNK})), c -> {summed('c')})"
    joined = f"flatten(zip_with(q, {summed(f'transform(q, c -> {last.format("c")})')}, (c, o) -> transform(c, e -> e + o - c[size(c) - 1])))"
    return f"transform(array({lengths}), a -> transform(array({parts}), q -> {joined})[0])[0]"


def matches(shape: str, valid: str = "true") -> str:
    """SQL of array<struct<start, end, value, patterns>>: the leftmost non-overlapping matches in `text` that are valid."""
    ends = running("zip_with(slice(x.p, 1, size(x.h)), x.h, (b, h) -> length(b) + length(h))")
    hit = "struct(x.e[i] - length(v) as start, x.e[i] as `end`, v as value, x.p[i] as before, x.p[i + 1] as after, i = 0 as first)"
    found = f"transform(array(struct(split(text, r'{shape}', -1) as p, regexp_extract_all(text, r'{shape}', 0) as h)), x -> struct(x.p as p, x.h as h, {ends} as e))"
    found = f"transform({found}, x -> transform(x.h, (v, i) -> {hit}))[0]"
    return f"transform(filter({found}, m -> {valid}), m -> struct(m.start as start, m.`end` as `end`, m.value as value, {patterns('m.before', 'm.after', 'm.first')} as patterns))"


def scanned(docs: DataFrame, id_col: str = "doc_id", text: str = "text", keep: bool = False) -> DataFrame:
    """(doc_id, base, seeds, candidates): base spans by kind and start; entities and free tokens with their patterns.

    With `keep`, also the whole row of `docs`.
    """
    rest = ["doc"] * keep
    none = f"cast(array() as {MATCHES})"
    rows = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"), F.struct(*docs.columns).alias("doc"))
    every = [f"transform(if({MAY[k]}, {matches(SHAPES[k], VALID[k])}, {none}), m -> struct({i} as kind, m.start as start, m.`end` as `end`, m.value as value, m.patterns as patterns))" for i, k in enumerate(KINDS)]
    loose = rf"if(text rlike r'[0-9@]|\[at\]', {matches(CANDIDATE)}, {none})"
    rows = rows.selectExpr("doc_id", *rest, f"concat({', '.join(every)}) as base", f"{loose} as loose")
    trimmed = f"if(rtrim('{TRAILING}', c.value) = '', c.value, rtrim('{TRAILING}', c.value))"
    free = rf"struct(c.start as start, c.start + length(v) as `end`, v rlike r'@|\[at\]' as at, if({IS_SECRET}, {len(KINDS)}, -1) as kind, xxhash64(v) as value, c.patterns as patterns)"
    return rows.selectExpr(
        "doc_id", *rest,
        "transform(base, b -> struct(b.kind as kind, b.start as start, b.`end` as `end`)) as base",
        "transform(base, b -> struct(b.kind as kind, xxhash64(b.value) as value, b.patterns as patterns)) as seeds",
        f"transform(filter(loose, c -> not exists(base, b -> b.start < c.`end` and c.start < b.`end`)), c -> transform(array({trimmed}), v -> {free})[0]) as candidates",
    )


def numbered(found: DataFrame) -> DataFrame:
    """`found` with a number of each row, for `widened`; it holds once the result is written."""
    return found.withColumn("row", F.monotonically_increasing_id())


def learn(docs: DataFrame, found: DataFrame, text: str = "text", scratch: Scratch | None = None, rounds: int = ROUNDS) -> DataFrame | None:
    """(pattern, kind) of all sure patterns by hash, from the pattern-instance graph of `found` and all places of the patterns in `docs`; None without any."""
    scratch = scratch or Scratch(docs.sparkSession, "pii")
    pattern = lambda c: F.explode(F.array_compact(c)).alias("pattern")
    known = found.select(F.explode("seeds").alias("s")).select("s.kind", "s.value", pattern(F.col("s.patterns")))
    free = found.select(F.explode("candidates").alias("c")).select("c.kind", "c.value", pattern(F.col("c.patterns")))
    edges = known.unionByName(free).groupBy("pattern", "value", "kind").agg(F.count("*").alias("n"))
    support = edges.groupBy("pattern").agg(F.count_if(F.col("kind") >= 0).alias("seeds"), F.sum("n").alias("n_seen")).where(F.col("seeds") >= SEEDS)
    likely = scratch.write(support, "likely")
    n_likely = likely.count()
    if not n_likely:
        return None
    three = "zip_with(zip_with(w, slice(w, 2, greatest(size(w) - 1, 0)), (a, b) -> struct(a, b)), slice(w, 3, greatest(size(w) - 2, 0)), (x, c) -> struct(x.a as a, x.b as b, c))"
    grams = docs.select(F.coalesce(F.col(text), F.lit("")).alias("text")).selectExpr(f"{words('text')} as w").selectExpr(f"explode(flatten(transform({three}, x -> {keys('x.a', 'x.b', 'x.c')}))) as pattern")
    if n_likely <= SENT:
        grams = grams.join(F.broadcast(likely.select("pattern")), "pattern")
    places = grams.groupBy("pattern").agg(F.count("*").alias("places"))
    special = likely.join(places, "pattern", "left").select("pattern", (F.col("n_seen") / F.greatest(F.col("n_seen"), F.coalesce("places", F.lit(0)))).alias("special"))
    special = scratch.write(special.where(F.col("special") >= SURE), "special")
    if special.isEmpty():
        return None
    graph = scratch.write(edges.join(special.select("pattern"), "pattern", "left_semi"), "graph")
    nodes = graph.groupBy("value").agg(F.max("kind").alias("kind"))
    seeds = nodes.where("kind >= 0")
    sure = seeds.select("value", "kind", F.lit(1.0).alias("sure"))
    pairs = graph.select("pattern", "value").distinct()
    scores = None
    for _ in range(rounds):
        totals = pairs.groupBy("pattern").agg(F.count("*").alias("instances"))
        scores = pairs.join(sure, "value").groupBy("pattern", "kind").agg(F.sum("sure").alias("known")).join(totals, "pattern").join(special, "pattern")
        scores = scratch.write(scores.select("pattern", "kind", (F.col("known") / F.col("instances") * F.col("special")).alias("sure")), "scores")
        doubt = F.sum(F.log(F.greatest(F.lit(1e-6), 1 - F.col("sure"))))
        reached = pairs.join(seeds, "value", "left_anti").join(scores, "pattern").groupBy("value", "kind").agg((1 - F.exp(doubt)).alias("sure")).where(F.col("sure") >= SURE)
        reached = scratch.write(reached, "reached")
        if reached.isEmpty():
            break  # nothing new counts: the scores stay
        sure = seeds.select("value", "kind", F.lit(1.0).alias("sure")).unionByName(reached)
    best = F.max_by("kind", F.struct("sure", -F.col("kind"))).alias("kind")
    patterns = scratch.write(scores.where(F.col("sure") >= SURE).groupBy("pattern").agg(best), "patterns")
    return None if patterns.isEmpty() else patterns


def widened(found: DataFrame, patterns: DataFrame | None) -> DataFrame:
    """Numbered `found` with `spans`: base and added spans by kind, then start.  A candidate's first sure pattern counts; only addresses are e-mail."""
    if patterns is None:
        return found.withColumn("spans", F.col("base"))
    free = found.select("row", F.explode("candidates").alias("c")).select("row", "c.start", "c.end", "c.at", F.posexplode("c.patterns").alias("turn", "pattern"))
    met = free.where(F.col("pattern").isNotNull()).join(patterns, "pattern").where(F.col("at") == (F.col("kind") == 0)).groupBy("row", "start", "end").agg(F.min_by("kind", "turn").alias("kind"))
    added = met.groupBy("row").agg(F.collect_list(F.struct("kind", "start", "end")).alias("added"))
    return found.join(added, "row", "left").withColumn("spans", F.array_sort(F.concat("base", F.coalesce("added", F.array().cast(f"array<{SPAN}>"))))).drop("added")


def find(docs: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, base, spans) as arrays of (kind index, start, end)."""
    scratch = Scratch(docs.sparkSession, "pii")
    found = scratch.write(numbered(scanned(docs, id_col, text)), "found")
    return widened(found, learn(docs, found, text, scratch)).select("doc_id", "base", "spans")


def _of_kind(i: int):
    return lambda s: s["kind"] == i


def listed(spans: str | Column) -> Column:
    names = F.array(*map(F.lit, FOUND))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"], s["end"])), ",")


def digests(found: DataFrame) -> DataFrame:
    """Counts and lists of base spans, of all spans of the base kinds, and of secrets beside them; `n_spans` counts all."""
    counts = [F.size(F.filter("base", _of_kind(i))).cast("long").alias(f"n_{k}") for i, k in enumerate(KINDS)]
    of_base, secret = F.filter("spans", lambda s: s["kind"] < len(KINDS)), F.filter("spans", _of_kind(len(KINDS)))
    return found.select("doc_id", *counts, F.sha2(listed("base"), 256).alias("base_sha256"), listed(of_base).alias("spans"), F.size(secret).cast("long").alias("n_secret"), listed(secret).alias("secrets"), F.size("spans").cast("long").alias("n_spans"))


def redact(docs: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """`docs` with every span replaced by its kind in angle brackets; overlapping spans are replaced together."""
    scratch = Scratch(docs.sparkSession, "pii")
    found = scratch.write(numbered(scanned(docs, id_col, text, keep=True)), "found")
    names = F.array(*[F.lit(f"<{k}>") for k in FOUND])
    spans_ = F.transform("spans", lambda m: F.struct(m["start"].alias("start"), m["end"].alias("end"), m["kind"].alias("kind")))
    out = widened(found, learn(docs, found, text, scratch)).select("doc", F.coalesce(F.col("doc")[text], F.lit("")).alias("text"), spans_.alias("base"))
    state = "struct<at:int,out:string>"

    def step(acc, s):
        skip = s["end"] <= acc["at"]
        piece = F.when(s["start"] >= acc["at"], F.concat(acc["out"], F.substring(F.col("text"), acc["at"] + 1, s["start"] - acc["at"]), F.element_at(names, s["kind"] + 1))).otherwise(acc["out"])
        return F.when(skip, acc).otherwise(F.struct(s["end"].alias("at"), piece.alias("out")).cast(state))

    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out")).cast(state)
    new = F.aggregate(F.array_sort("base"), start, step, lambda acc: F.concat(acc["out"], F.substring(F.col("text"), acc["at"] + 1, F.length("text"))))
    new = F.when(F.col("doc")[text].isNull(), F.lit(None)).when(F.size("base") == 0, F.col("doc")[text]).otherwise(new)
    return out.select(new.alias("new"), "doc").select(*[(F.col("new") if c == text else F.col("doc")[c]).alias(c) for c in docs.columns])
