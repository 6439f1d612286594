"""Removal of repeated runs of lines, by winnowing over line hashes; DataFrame functions only.

Lines with a word are hashed. Of every window of RUN neighbouring lines the least hash (the leftmost of equals) is selected,
so any two equal runs of RUN lines have selected the same line: it is their guaranteed fingerprint. Only selected
positions are written, with the RUN - 1 lines before and after them. Positions whose fingerprint is found once are dropped;
the others are joined on it and extended to both sides, line by line, to each run of RUN lines that selected them. A run
that occurred before (by doc_id, then place) loses all its lines; longer runs are unions of such. A line of LONG words or
more is a run by itself.

Equal fingerprints of a third of all rows are spread by a salt and pre-aggregated to one row per extension. Fingerprints are
told apart by 128 bits of hash, the lines beside them by 64 more each.

Defined results: a null or empty text has no lines and stays as it is; lines without a word are neither compared nor
removed; rows that repeat both id and text are one document and get the same result; a null doc_id comes last; of equal
ids with different texts either may come first; an empty table gives an empty result; a very long text takes time in
proportion to its lines; other columns are kept by `without_repeats`, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

RUN = 2
LONG = 50
#: Shares that the rows of one fingerprint are dealt to.
SALTS = 16
_WORD = "[^\\x20\\x09-\\x0D]"


def _lines(text: Column, long: int) -> Column:
    """The lines with a word: their number i in the text, two hashes, and whether each is long."""
    every = F.transform(F.split(text, "\n", -1), lambda x, i: F.struct(i.alias("i"), F.xxhash64(x).alias("a"), F.xxhash64(F.lit("second"), x).alias("b"), F.rlike(x, F.lit(_WORD)).alias("ok"), (F.regexp_count(x, F.lit(_WORD + "+")) >= long).alias("long")))
    return F.filter(every, lambda x: x.ok)


def positions(docs: DataFrame, run: int = RUN, long: int = LONG) -> DataFrame:
    """(doc_id, key, a, b, place, before, after, ahead, alone): selected positions. a and b hash the line; `before` (read
    leftwards) and `after` hold its neighbours' first hashes; place counts lines with a word from 1; ahead is a bit mask of how
    many lines come before it in the runs that selected it; alone says that it is a run by itself. docs are `keyed`."""
    none = F.expr("cast(array() as array<int>)")

    def least(h: Column) -> Column:
        starts = F.when(F.size(h) >= run, F.sequence(F.lit(1), F.size(h) - (run - 1))).otherwise(none)
        return F.transform(starts, lambda j: F.array_min(F.slice(h, j, run))["at"])

    def position(h: Column, selected: Column, place: Column) -> Column:
        # the runs that selected a place start at most run - 1 lines before it
        first, own = F.greatest(F.lit(1), place - (run - 1)), F.element_at(h, place)
        ahead = F.filter(F.transform(F.slice(selected, first, run), lambda p, n: F.when(p == place, place - first - n)), lambda x: x.isNotNull() & (x >= 0))
        before, after = F.reverse(F.transform(F.slice(h, first, place - first), lambda x: x.a)), F.transform(F.slice(h, place + 1, run - 1), lambda x: x.a)
        return F.struct(own["a"].alias("a"), own["b"].alias("b"), place.alias("place"), before.alias("before"), after.alias("after"), _mask(ahead).alias("ahead"), own["long"].alias("alone"))

    def selected_positions(s: Column) -> Column:
        places = F.array_distinct(F.concat(s.least, F.transform(F.filter(s.h, lambda x: x.long), lambda x: x["at"])))
        return F.transform(places, lambda place: position(s.h, s.least, place))

    numbered = F.transform(_lines(F.col("text"), long), lambda x, n: F.struct(x.a.alias("a"), x.b.alias("b"), (n + 1).alias("at"), x.long.alias("long")))
    found = common.let(numbered, lambda h: common.let(F.struct(h.alias("h"), least(h).alias("least")), selected_positions))
    return docs.select("doc_id", "key", F.inline(found))


def _mask(numbers: Column) -> Column:
    return F.aggregate(numbers, F.lit(0), lambda m, x: m.bitwiseOR(F.call_function("shiftleft", F.lit(1), x)))


def _runs(run: int) -> Column:
    """(length, ahead) of the runs that a position stands for."""
    chosen = [F.when(F.col("ahead").bitwiseAND(F.lit(1 << n)) != 0, F.struct(F.lit(run).alias("length"), F.lit(n).alias("ahead"))) for n in range(run)]
    return F.array_compact(F.array(*chosen, F.when(F.col("alone"), F.struct(F.lit(1).alias("length"), F.lit(0).alias("ahead")))))


def _salted(df: DataFrame) -> DataFrame:
    return df.withColumn("salt", F.pmod(F.xxhash64("key", "place"), F.lit(SALTS)).cast("int"))


def _all_salts(df: DataFrame) -> DataFrame:
    return df.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))


def repeated_lines(docs: DataFrame, run: int = RUN, long: int = LONG) -> DataFrame:
    """(doc_id, key, gone): numbers, among its lines with a word and from 1, of a document's lines to remove."""
    found = common.materialise(positions(docs, run, long))
    twice = found.groupBy("a", "b").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("a", "b")
    met = _salted(found).join(_all_salts(twice), ["a", "b", "salt"], "left_semi")
    # extension: a run's lines are the fingerprint with so many lines to its left and the rest to its right
    extended = met.select("doc_id", "key", "a", "b", "place", "salt", "before", "after", F.explode(_runs(run)).alias("r")).select(
        "doc_id", "key", "a", "b", "place", "salt", F.col("r.length").alias("length"), F.col("r.ahead").alias("ahead"),
        F.slice("before", F.lit(1), F.col("r.ahead")).alias("left"), F.slice("after", F.lit(1), F.col("r.length") - F.col("r.ahead") - 1).alias("right"),
    )
    same = ["a", "b", "length", "left", "right"]
    order = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "key", "place")
    first = extended.groupBy(*same).agg(F.min(order).alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").drop("n")
    later = extended.join(_all_salts(first), [*same, "salt"]).where((F.col("key") != F.col("first.key")) | ~F.col("doc_id").eqNullSafe(F.col("first.doc_id")) | (F.col("place") != F.col("first.place")))
    start = F.col("place") - F.col("ahead")
    return later.select("doc_id", "key", F.explode(F.sequence(start, start + F.col("length") - 1)).alias("line")).groupBy("doc_id", "key").agg(F.collect_set("line").alias("gone"))


def marked(docs: DataFrame, run: int = RUN, long: int = LONG) -> DataFrame:
    """Wrapped docs with `lines` (all of them) and `gone` (numbers of those to remove, from 0, or null)."""
    gone = repeated_lines(common.keyed(docs), run, long).select(F.col("key").alias("g_key"), F.col("doc_id").alias("g_doc"), F.col("gone").alias("g_gone"))
    joined = common.wrapped(docs).join(gone, (F.col("key") == F.col("g_key")) & F.col("row.doc_id").eqNullSafe(F.col("g_doc")), "left")
    lines = F.split(common.row_text(), "\n", -1)
    worded = F.filter(F.transform(lines, lambda x, i: F.when(F.rlike(x, F.lit(_WORD)), i)), lambda i: i.isNotNull())
    gone = F.when(F.col("g_gone").isNotNull(), common.let(worded, lambda w: F.transform("g_gone", lambda n: F.element_at(w, n))))
    return joined.select("row", gone.alias("gone"), lines.alias("lines"))


def _kept() -> Column:
    numbers = F.array_except(F.sequence(F.lit(0), F.size("lines") - 1), F.col("gone"))
    return common.let(F.col("lines"), lambda lines: F.array_join(F.transform(numbers, lambda i: F.get(lines, i)), "\n"))


def without_repeats(docs: DataFrame, run: int = RUN, long: int = LONG) -> DataFrame:
    """docs with the later copies of repeated runs cut from `text`; a document left without a word by this goes."""
    m = marked(docs, run, long).withColumn("new", F.when(F.col("gone").isNotNull(), _kept()))
    return common.with_text(m.where(F.col("new").isNull() | F.rlike("new", F.lit(_WORD))), docs)


def op2_line_dedup(spark, sf_dir: str) -> DataFrame:
    """Per document: lines, lines removed, and a digest of what is left; defined results as in the module's docstring."""
    m = marked(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
    kept = F.when(F.col("gone").isNull(), common.row_text()).otherwise(_kept())
    return m.select(F.col("row.doc_id").alias("doc_id"), F.size("lines").cast("long").alias("n_lines"), F.greatest(F.size("gone"), F.lit(0)).cast("long").alias("n_removed"), F.sha2(kept, 256).alias("kept_sha256"))
