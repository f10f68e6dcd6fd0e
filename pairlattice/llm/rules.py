"""Quality rules with DataFrame functions only: word statistics and cross-document line frequency.

Lines are normalised and hashed, distinct texts are counted per host and line, lines above the limit
are removed, and a document that loses more than its allowed share of words is rejected.

Defined results: null text has no words, counts as an empty one and fails the base rule; a null host is a host
of its own; equal texts of a host count once, so copies alone never make a line frequent; repeated rows each get
a row; an empty table gives none; columns beyond those named are ignored.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pairlattice.llm.common import cut

GAP = r"[\x20\x09-\x0D]+"
WINDOW = 8


@dataclass(frozen=True)
class RuleLimits:
    """A line is removed when more than ``line_share`` of its host's distinct texts, and more than ``line_docs``, hold it."""

    line_share: float = 0.10
    line_docs: int = 20
    lost_share: float = 0.5
    least_words: int = 20
    repeat_percent: int = 30
    #: Rows of the host table that may be broadcast; each holds at most (mean lines of a text) / line_share hashes.
    broadcast_hosts: int = 20_000


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body(value)`` with ``value`` evaluated once, also where ``body`` uses it inside a lambda."""
    return F.element_at(F.transform(F.array(value), body), 1)


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), GAP), "")


def covered_words(words: Column) -> Column:
    """Words inside windows of eight words that occur at least twice, the first occurrence included."""

    def covered(hashes: Column) -> Column:
        def among(ordered: Column) -> Column:
            same = lambda x, i: (F.get(ordered, i - 1)["h"] == x["h"]) | (F.get(ordered, i + 1)["h"] == x["h"])
            at = F.sort_array(F.transform(F.filter(ordered, lambda x, i: F.coalesce(same(x, i), F.lit(False))), lambda x: x["i"]))
            begin = F.struct(F.lit(-WINDOW).alias("last"), F.lit(0).alias("sum"))
            return F.aggregate(at, begin, lambda a, p: F.struct(p.alias("last"), (a["sum"] + F.least(F.lit(WINDOW), p - a["last"])).alias("sum")), lambda a: a["sum"])

        repeats = let(F.sort_array(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i")))), among)
        return F.when(F.size(F.array_distinct(hashes)) == F.size(hashes), F.lit(0)).otherwise(repeats)

    # keys of 1 and 8 words; equal windows have equal keys, other ones within a text differ but for a chance of 2^-64 a pair
    def windows(keys: Column) -> Column:
        return F.transform(F.sequence(F.lit(1), F.size(keys) - (WINDOW - 1)), lambda i: F.xxhash64(F.slice(keys, i, WINDOW)))

    several = let(F.transform(words, lambda w: F.xxhash64(w)), lambda keys: let(windows(keys), covered))
    return F.when(F.size(words) > WINDOW, several).otherwise(F.lit(0)).cast("long")


def normalised(line: Column) -> Column:
    """White space runs become one space, A-Z small letters, digits 0."""
    return F.trim(F.regexp_replace(F.regexp_replace(F.translate(line, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), "[0-9]", "0"), GAP, " "))


def lines_of(text: Column) -> Column:
    """Lines with a word, as they are."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))


def statistics(docs: DataFrame) -> DataFrame:
    """``docs`` with n_words, word_chars, n_symbols, n_dup_lines and n_repeat_words; row by row."""
    text = F.coalesce("text", F.lit(""))
    parts = let(words_of(text), lambda w: F.struct(F.size(w).cast("long").alias("n_words"), F.length(F.array_join(w, "")).cast("long").alias("word_chars"), covered_words(w).alias("n_repeat_words")))
    lines = let(lines_of(text), lambda x: (F.size(x) - F.size(F.array_distinct(x))).cast("long"))
    symbols = (F.length(text) - F.length(F.regexp_replace(text, r"[#*$%&|<>]+", ""))).cast("long")
    return docs.withColumn("_s", parts).select("*", "_s.*", symbols.alias("n_symbols"), lines.alias("n_dup_lines")).drop("_s")


def frequent_lines(docs: DataFrame, host: str, limits: RuleLimits) -> DataFrame:
    """(host, frequent): line hashes above the limit of each host that has any."""
    text = F.coalesce("text", F.lit(""))
    keys = F.array_distinct(F.transform(lines_of(F.col("text")), lambda x: F.xxhash64(normalised(x))))
    rows = docs.select(F.col(host).alias("_host"), F.xxhash64(text, F.length(text)).alias("_text"), keys.alias("_keys"))
    texts = rows.groupBy("_host", "_text").agg(F.lit(1).alias("one")).groupBy("_host").agg(F.count("one").alias("_n"))
    # two counts, each combined before its shuffle: equal texts of a host first, then texts of a line
    once = rows.select("_host", "_text", F.explode("_keys").alias("_line")).distinct()
    counts = once.groupBy("_host", "_line").agg(F.count(F.lit(1)).alias("_docs")).where(F.col("_docs") > limits.line_docs)
    kept = counts.alias("c").join(texts.alias("t"), F.col("c._host").eqNullSafe(F.col("t._host")))
    return kept.where(F.col("_docs") > limits.line_share * F.col("_n")).groupBy(F.col("c._host").alias("_host")).agg(F.collect_list("_line").alias("_frequent"))


def remaining(text: Column, frequent: Column) -> Column:
    """``text`` without its lines above the limit; as it is where the host has none."""
    rest = F.filter(F.split(text, "\n", -1), lambda x: ~F.array_contains(frequent, F.xxhash64(normalised(x))))
    return F.when(frequent.isNull(), text).otherwise(F.array_join(rest, "\n"))


def quality_rules(docs: DataFrame, host: str = "source", limits: RuleLimits | None = None) -> DataFrame:
    """(doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, n_removed_words, kept, text).

    The statistics are those of the whole text; ``text`` is what is left without the lines above the
    limit, and its words decide how many were removed.
    """
    limits = limits or RuleLimits()
    docs = docs.select("doc_id", "text", F.col(host).alias("source"))
    frequent = bounded(frequent_lines(docs, "source", limits), limits)
    judged = statistics(docs).alias("d").join(frequent.alias("f"), F.col("d.source").eqNullSafe(F.col("f._host")), "left")
    judged = judged.withColumn("_rest", remaining(F.col("text"), F.col("_frequent")))
    lost = F.when(F.col("_frequent").isNull(), F.lit(0)).otherwise(F.col("n_words") - F.size(words_of(F.col("_rest")))).cast("long")
    base = (F.col("n_words") < limits.least_words) | (100 * F.col("n_repeat_words") > limits.repeat_percent * F.col("n_words"))
    return (
        judged.withColumn("n_removed_words", lost)
        .withColumn("base_failed", base)
        .select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "n_removed_words", (~F.col("base_failed") & (F.col("n_removed_words") <= limits.lost_share * F.col("n_words"))).alias("kept"), F.col("_rest").alias("text"))
    )


def bounded(frequent: DataFrame, limits: RuleLimits) -> DataFrame:
    """Broadcast the host table where its rows are few; else leave the join to the shuffle and its skew handling."""
    frequent = cut(frequent)
    return F.broadcast(frequent) if frequent.count() <= limits.broadcast_hosts else frequent


def cleaned(docs: DataFrame, host: str = "source", limits: RuleLimits | None = None) -> DataFrame:
    """``docs`` with the lines above the limit taken out of ``text``; other columns as they are."""
    limits = limits or RuleLimits()
    frequent = bounded(frequent_lines(docs, host, limits), limits)
    joined = docs.alias("d").join(frequent.alias("f"), F.col(f"d.`{host}`").eqNullSafe(F.col("f._host")), "left")
    return joined.select(*[(remaining(F.col("d.text"), F.col("f._frequent")).alias("text") if c == "text" else F.col(f"d.`{c}`")) for c in docs.columns])


def oracle(limits: RuleLimits | None = None) -> str:
    limits = limits or RuleLimits()
    norm = lambda x: f"trim(regexp_replace(regexp_replace(translate({x}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[0-9]', '0', 'g'), '[\\x20\\x09-\\x0D]+', ' ', 'g'))"
    words = lambda x: f"regexp_extract_all({x}, '[^\\x20\\x09-\\x0D]+')"
    return f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text, source FROM documents),
w AS (SELECT doc_id, {words('text')} AS words FROM d),
s AS (SELECT doc_id, CAST(len(words) AS BIGINT) AS n_words, CAST(length(array_to_string(words, '')) AS BIGINT) AS word_chars FROM w),
p AS (SELECT doc_id, words, unnest(range(1, len(words) - 6)) AS pos FROM w WHERE len(words) >= 8),
k AS (SELECT doc_id, pos, array_to_string(words[pos:pos + 7], ' ') AS gram FROM p),
r AS (SELECT doc_id, pos FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, gram) AS n FROM k) WHERE n > 1),
c AS (SELECT doc_id, CAST(count(DISTINCT pos + j) AS BIGINT) AS n FROM r, range(8) AS t(j) GROUP BY doc_id),
l AS (SELECT doc_id, source, text, line FROM (SELECT *, unnest(string_split(text, chr(10))) AS line FROM d) WHERE regexp_matches(line, '[^\\x20\\x09-\\x0D]')),
u AS (SELECT doc_id, CAST(count(*) - count(DISTINCT line) AS BIGINT) AS n FROM l GROUP BY doc_id),
h AS (SELECT source, count(DISTINCT text) AS n FROM d GROUP BY source),
f AS (SELECT l.source, {norm('line')} AS line FROM l JOIN h USING (source) GROUP BY 1, 2 HAVING count(DISTINCT text) > {limits.line_docs} AND count(DISTINCT text) > {limits.line_share} * any_value(h.n)),
x AS (SELECT doc_id, CAST(sum(len({words('l.line')})) AS BIGINT) AS n FROM l JOIN f ON l.source = f.source AND {norm('l.line')} = f.line GROUP BY doc_id),
a AS (SELECT d.doc_id, n_words, word_chars, CAST(length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
        coalesce(u.n, 0) AS n_dup_lines, coalesce(c.n, 0) AS n_repeat_words, coalesce(x.n, 0) AS n_removed_words
      FROM d JOIN s USING (doc_id) LEFT JOIN u USING (doc_id) LEFT JOIN c USING (doc_id) LEFT JOIN x USING (doc_id))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
  n_words < {limits.least_words} OR 100 * n_repeat_words > {limits.repeat_percent} * n_words AS base_failed, n_removed_words,
  NOT (n_words < {limits.least_words} OR 100 * n_repeat_words > {limits.repeat_percent} * n_words) AND n_removed_words <= {limits.lost_share} * n_words AS kept
FROM a
"""
