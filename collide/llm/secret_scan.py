"""Secret scan with a trigram inverted index; DataFrame functions only.

Each rule's expression gives a Boolean query of trigrams that every match contains. Postings (trigram, document) of those
trigrams alone are built in one scan, intersected per document as a bit mask, and the query is evaluated on the mask.
Candidates are joined back and verified by the expression itself; rules without a mandatory trigram scan every text.

Defined results: a null text is an empty one, without secrets; documents are keyed by id and text, so repeated rows get the
same spans; positions are in code points, end exclusive; an empty table gives an empty result; a very long text is scanned
whole, in time close to proportion; other columns are ignored by `scan` and kept by `redact`, whatever their names.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common, trigram_query


@dataclass(frozen=True)
class Rule:
    """A kind of secret: its expression, and the least length of one of its groups (0: the match)."""

    kind: str
    pattern: str
    group: int = 0
    least: int = 0


#: Expressions of secrets. The first three are the base kinds, in their order.
BASE = (
    Rule("assign", r"""([Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 8),
    Rule("access", r"AKIA[A-Z0-9]+", 0, 16),
    Rule("hex", r"[0-9a-f]{32,}"),  # runs are maximal, so shorter ones need no look
)
MORE = (
    Rule("private_key", r"-----BEGIN [A-Z ]*PRIVATE KEY-----"),
    Rule("code_host", r"gh[oprsu]_[A-Za-z0-9]{36,}"),
    Rule("chat_token", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("signed_token", r"eyJ[A-Za-z0-9_-]{10,}\.eyJ[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]+"),
)
RULES = BASE + MORE
MARK = "[SECRET]"

_SPAN = "array<struct<start:int,rank:int,end:int,kind:string>>"


def postings(docs: DataFrame, trigrams: list[str]) -> DataFrame:
    """The inverted index of the given trigrams: (trigram, key), trigram as its number in the list. One scan."""
    low = docs.select("key", F.lower("text").alias("low"))
    present = F.array_compact(F.array(*[F.when(F.contains("low", F.lit(t)), F.lit(i)) for i, t in enumerate(trigrams)]))
    return low.select("key", F.explode(present).alias("trigram"))


def _bits(query, number: dict[str, int], words: int) -> Column:
    """The query on a document's bit mask (mask0, mask1, ...)."""
    if query is True:
        return F.lit(True)
    if isinstance(query, str) or query[0] == "and":
        parts = [query] if isinstance(query, str) else list(query[1])
        plain = [number[p] for p in parts if isinstance(p, str)]
        out = None
        for w in range(words):
            need = sum(1 << (i % 62) for i in plain if i // 62 == w)
            if need:
                x = F.col(f"mask{w}").bitwiseAND(F.lit(need)) == F.lit(need)
                out = x if out is None else out & x
        for p in parts:
            if not isinstance(p, str):
                x = _bits(p, number, words)
                out = x if out is None else out & x
        return out
    out = None
    for p in query[1]:
        x = _bits(p, number, words)
        out = x if out is None else out | x
    return out


def candidates(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> tuple[DataFrame, list[str]]:
    """(key, may_<kind>...) of documents that satisfy some rule's query, and the kinds that have one."""
    queries = {r.kind: trigram_query.derive(r.pattern) for r in rules}
    indexed = {k: q for k, q in queries.items() if q is not True}
    listed = sorted(set().union(*(trigram_query.trigrams(q) for q in indexed.values()), set()))
    number = {t: i for i, t in enumerate(listed)}
    words = len(listed) // 62 + 1
    hits = postings(docs, listed) if listed else docs.select("key", F.lit(0).alias("trigram")).limit(0)
    bit = F.expr("shiftleft(1L, cast(trigram % 62 as int))")
    mask = hits.groupBy("key").agg(*[F.bit_or(F.when(F.floor(F.col("trigram") / 62) == w, bit).otherwise(F.lit(0).cast("long"))).alias(f"mask{w}") for w in range(words)])
    flags = mask.select("key", *[_bits(q, number, words).alias(f"may_{k}") for k, q in indexed.items()])
    some = None
    for k in indexed:
        some = F.col(f"may_{k}") if some is None else some | F.col(f"may_{k}")
    return (flags.where(some) if some is not None else flags), list(indexed)


#: Elements of an array folded in one go: a fold copies what it has at each step, so long arrays are folded part by part.
PART = 64


def _parts(array: Column) -> Column:
    """An array cut in parts of PART elements; an empty one has no parts."""

    def cut(a: Column) -> Column:
        numbers = F.when(F.size(a) > 0, F.sequence(F.lit(0), F.floor((F.size(a) - 1) / PART).cast("int"))).otherwise(F.expr("cast(array() as array<int>)"))
        return F.transform(numbers, lambda i: F.slice(a, i * PART + 1, PART))

    return common.let(array, cut)


def _running(values: Column, fold) -> Column:
    """What `fold` has before each element, from 0: as many entries as elements."""
    start = F.struct(F.lit(0).alias("now"), F.expr("cast(array() as array<int>)").alias("before"))
    return F.aggregate(values, start, lambda acc, x: F.struct(fold(acc.now, x).cast("int").alias("now"), F.concat(acc.before, F.array(acc.now)).alias("before")), lambda acc: acc.before)


def _starts(lengths: Column) -> Column:
    """Where each of the pieces of these lengths starts, part by part."""
    total = lambda part: F.aggregate(part, F.lit(0), lambda t, x: t + x)
    plus = lambda t, x: t + x
    within = lambda part, at: F.transform(_running(part, plus), lambda x: x + at)
    return common.let(_parts(lengths), lambda parts: F.flatten(F.zip_with(parts, _running(F.transform(parts, total), plus), within)))


def _matches(text: Column, rule: Rule, rank: int) -> Column:
    """Spans of the rule's matches: what lies between them and their own lengths, summed up from the left."""
    pattern = F.lit(rule.pattern)
    whole = F.regexp_extract_all(text, pattern, F.lit(0))
    judged = F.regexp_extract_all(text, pattern, F.lit(rule.group)) if rule.group else whole
    none = F.expr(f"cast(array() as {_SPAN})")

    def spans(x: Column) -> Column:
        gaps = F.transform(F.slice(x.around, 1, F.size(x.whole)), lambda b: F.length(b))
        steps = F.zip_with(gaps, x.whole, lambda b, m: b + F.length(m))
        places = F.zip_with(_starts(steps), gaps, lambda at, b: at + b)
        pairs = F.zip_with(x.whole, x.judged, lambda m, g: F.struct(F.length(m).alias("m"), F.length(g).alias("g")))
        found = F.zip_with(places, pairs, lambda at, y: F.when(y.g >= rule.least, F.struct(at.alias("start"), F.lit(rank).alias("rank"), (at + y.m).alias("end"), F.lit(rule.kind).alias("kind"))))
        return F.filter(found, lambda f: f.isNotNull())

    pieces = F.struct(F.split(text, rule.pattern, -1).alias("around"), whole.alias("whole"), judged.alias("judged"))
    return F.when(F.rlike(text, pattern), common.let(pieces, spans)).otherwise(none)


def _found(joined: DataFrame, rules: tuple[Rule, ...], indexed: list[str]) -> Column:
    none = F.expr(f"cast(array() as {_SPAN})")
    each = []
    for rank, r in enumerate(rules):
        spans = _matches(F.col("text"), r, rank)
        each.append(F.when(F.col(f"may_{r.kind}"), spans).otherwise(none) if r.kind in indexed else spans)
    return F.array_sort(F.concat(*each))


def with_spans(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """Wrapped docs with `spans`, sorted by start and then by kind as listed."""
    w = common.wrapped(docs)
    found, indexed = candidates(w.select("key", common.row_text().alias("text")), rules)
    joined = w.join(found.withColumnRenamed("key", "f_key"), F.col("key") == F.col("f_key"), "left").withColumn("text", common.row_text())
    return joined.select("row", "text", _found(joined, rules, indexed).alias("spans"))


def _written(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s.kind, s.start.cast("string"), s.end.cast("string"))), ",")


def scan(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """doc_id, the counts of base kinds, base_sha256, spans, n_spans: a row per row of docs."""
    base = [r.kind for r in BASE]

    def of(kind: str) -> Column:
        return F.size(F.filter("spans", lambda s: s.kind == kind)).cast("long").alias(f"n_{kind}")

    found = with_spans(docs.select("doc_id", "text"), rules)
    digest = F.sha2(_written(F.filter("spans", lambda s: s.kind.isin(*base))), 256)
    return found.select(F.col("row.doc_id").alias("doc_id"), *map(of, base), digest.alias("base_sha256"), _written(F.col("spans")).alias("spans"), F.size("spans").cast("long").alias("n_spans"))


def redact(docs: DataFrame, rules: tuple[Rule, ...] = RULES, mark: str = MARK) -> DataFrame:
    """docs with every secret in `text` replaced by a mark, and n_chars, where there is one, counted anew; overlapping spans share one mark."""

    def piece(part: Column, at: Column) -> Column:
        # the text from where the parts before this one have reached to this one's farthest end, with marks
        end = F.greatest(at, F.array_max(F.transform(part, lambda s: s.end)))

        def cut(region: Column) -> Column:
            def step(acc: Column, s: Column) -> Column:
                plain = F.substring(region, acc.at - at + 1, s.start - acc.at)
                return F.when(s.start >= acc.at, F.struct(s.end.alias("at"), F.concat(acc.out, plain, F.lit(mark)).alias("out"))).otherwise(F.struct(F.greatest(acc.at, s.end).alias("at"), acc.out.alias("out")))

            return F.aggregate(part, F.struct(at.alias("at"), F.lit("").alias("out")), step, lambda acc: acc.out)

        return common.let(F.substring(F.col("text"), at + 1, end - at), cut)

    def marked(parts: Column) -> Column:
        reach = lambda part: F.array_max(F.transform(part, lambda s: s.end))
        at = _running(F.transform(parts, reach), lambda now, x: F.greatest(now, x))
        rest = F.substring(F.col("text"), F.array_max(F.transform(parts, reach)) + 1, F.length("text"))
        return F.concat(F.array_join(F.zip_with(parts, at, piece), ""), rest)

    cleaned = common.let(_parts(F.col("spans")), marked)
    found = with_spans(docs, rules)
    return common.with_text(found.withColumn("new", F.when(F.size("spans") > 0, cleaned)), docs)


def op1_secret_scan(spark, sf_dir: str) -> DataFrame:
    """Spans, counts and digest of every document; defined results as in the module's docstring."""
    return scan(spark.read.parquet(f"{sf_dir}/documents.parquet"))
