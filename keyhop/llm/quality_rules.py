"""Quality rules: counts within a document, and line frequency across the documents of a host.

All of it is DataFrame expressions. One pass over the texts gives each document's counts and the hashes
of its normalised lines; the rest works on that much smaller table. Within a document, five-word
windows are compared by a 64-bit hash: equal ones are neighbours in sorted order, and the words they
cover are counted as a union of intervals. Across documents, the number of documents of a host that
hold a line is a plain count with partial aggregation, so neither a large host nor a common line
gathers in one task. Lines above the limits are removed, and a document of which too little is left is
rejected.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyhop.runtime import Scratch

WINDOW = 5
#: Java patterns: white space between words, a line with a word, what is no symbol.
_BLANKS = r"[ \t-\r]+"
_WORDED = r"[^ \t-\r]"
_NO_SYMBOL = r"[^#*$%&|<>]+"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body(value)`` with the value computed once, however often and however deep ``body`` uses it.

    Inside a lambda Spark evaluates an outer expression anew for every element; a lambda's own variable
    is held.
    """
    return F.get(F.transform(F.array(value), body), 0)


def words_of(text: Column) -> Column:
    """The maximal runs of characters other than ASCII white space."""
    return F.filter(F.split(text, _BLANKS), lambda w: w != "")


def covered(starts: Column) -> Column:
    """Length of the union of five-word intervals at sorted start positions."""
    gaps = F.transform(starts, lambda at, k: F.least(F.coalesce(F.get(starts, k + 1) - at, F.lit(WINDOW)), F.lit(WINDOW)))
    return F.aggregate(gaps, F.lit(0).cast("bigint"), lambda a, x: a + x)


def repeated_words(words: Column) -> Column:
    """How many words stand in windows of five words that occur twice or more, the first included.

    The hashes' number of distinct values tells at once whether any window repeats; only then are the
    windows sorted. Each repeated start covers five words, less those that the next one covers as well.
    """

    def hashes(ws: Column) -> Column:
        last = F.size(ws) - WINDOW
        starts = F.when(last >= 0, F.sequence(F.lit(0), last)).otherwise(F.array().cast("array<int>"))
        return F.transform(starts, lambda i: F.xxhash64(*(F.get(ws, i + k) for k in range(WINDOW))))

    def again(ordered: Column) -> Column:
        def same(k: Column, other: Column) -> Column:
            return F.coalesce(F.get(ordered, k)["h"] == F.get(ordered, other)["h"], F.lit(False))

        return F.transform(F.filter(ordered, lambda x, k: same(k, k + 1) | ((k > 0) & same(k, k - 1))), lambda x: x["i"])

    def count(hs: Column) -> Column:
        ordered = F.sort_array(F.transform(hs, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        return F.when(F.size(F.array_distinct(hs)) == F.size(hs), F.lit(0).cast("bigint")).otherwise(let(ordered, lambda o: let(F.sort_array(again(o)), covered)))

    return let(words, lambda ws: let(hashes(ws), count))


def document_rules(df: DataFrame) -> DataFrame:
    """Adds ``n_words``, ``word_chars``, ``n_symbols``, ``n_dup_lines``, ``n_repeat_words`` for column ``text`` (not null)."""
    df = df.withColumn("words", words_of(F.col("text")))
    duplicates = let(F.filter(F.split("text", "\n"), lambda x: x.rlike(_WORDED)), lambda ls: F.size(ls) - F.size(F.array_distinct(ls)))
    return df.withColumns(
        {
            "n_words": F.size("words").cast("bigint"),
            "word_chars": F.length(F.array_join("words", "")).cast("bigint"),
            "n_symbols": F.length(F.regexp_replace("text", _NO_SYMBOL, "")).cast("bigint"),
            "n_dup_lines": duplicates.cast("bigint"),
            "n_repeat_words": repeated_words(F.col("words")),
        }
    ).drop("words")


def normalised_lines(text: Column) -> Column:
    """A document's lines with a word as (hash, characters): lower case, trimmed, digits folded; the characters are those before folding."""
    folded = F.lower(F.regexp_replace(text, "[0-9]+", "0"))
    lines = F.zip_with(F.split(folded, "\n"), F.split(text, "\n"), lambda x, own: F.struct(F.trim(x).alias("x"), F.length(F.trim(own)).alias("chars")))
    return F.transform(F.filter(lines, lambda y: y["x"].rlike(_WORDED)), lambda y: F.struct(F.xxhash64(y["x"]).alias("line"), y["chars"].alias("chars")))


def removed_characters(df: DataFrame, scratch: Scratch, min_documents: int, min_share: float, broadcast_rows: int = 200_000) -> DataFrame:
    """For each row (columns ``row``, ``host``, ``lines``) with a removed line: ``removed_row``, ``removed_chars``.

    A line is removed where more than ``min_documents`` documents of its host and more than
    ``min_share`` of them hold it. The frequent lines are broadcast only where they were counted to be
    at most ``broadcast_rows``; beyond that the join is a shuffle whose skewed side Spark can split.
    """
    held = df.select("host", F.explode(F.array_distinct(F.col("lines.line"))).alias("line"))
    often = held.groupBy("host", "line").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > min_documents)
    if min_share > 0:
        hosts = df.groupBy(F.col("host").alias("of_host")).agg(F.count(F.lit(1)).alias("documents"))
        often = often.join(hosts, F.col("host").eqNullSafe(F.col("of_host"))).where(F.col("n") > min_share * F.col("documents"))
    often = scratch.save(often.select(F.col("host").alias("often_host"), F.col("line").alias("often_line")), "frequent_lines")
    each = df.select("row", "host", F.explode("lines").alias("x")).select("row", "host", "x.line", "x.chars")
    keys = F.broadcast(often) if often.count() <= broadcast_rows else often
    hit = each.join(keys, (F.col("line") == F.col("often_line")) & F.col("host").eqNullSafe(F.col("often_host")), "left_semi")
    return hit.groupBy(F.col("row").alias("removed_row")).agg(F.sum("chars").cast("bigint").alias("removed_chars"))


def apply_rules(
    df: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    host_col: str = "source",
    min_words: int = 10,
    max_repeat_percent: int = 20,
    min_documents: int = 20,
    min_share: float = 0.0,
    max_removed: float = 0.8,
) -> DataFrame:
    """The rules' counts, ``base_failed``, ``removed_chars`` and ``kept`` for every row of ``df``.

    ``base_failed``: fewer than ``min_words`` words, or more than ``max_repeat_percent`` percent of the
    words in repeated windows. ``kept`` is false for those, and for documents of which removed lines
    make up more than ``max_removed`` of the characters of all its lines with a word. A null text has no word; a null host is a host
    of its own. Each row counts as one document; rows with equal ids share the sum of their removed
    characters. Other columns are not read. An empty table gives an empty result.
    """
    scratch = Scratch(df.sparkSession, "quality-rules")
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = df.select(F.col(id_col).alias("row"), F.col(host_col).alias("host"), text.alias("text"))
    parsed = document_rules(rows.withColumn("lines", normalised_lines(F.col("text")))).drop("text")
    parsed = parsed.withColumn("line_chars", F.aggregate("lines", F.lit(0).cast("bigint"), lambda a, x: a + x["chars"]))
    parsed = scratch.save(parsed, "parsed")
    removed = removed_characters(parsed, scratch, min_documents, min_share)
    joined = parsed.drop("lines", "host").join(removed, F.col("row").eqNullSafe(F.col("removed_row")), "left")
    failed = (F.col("n_words") < min_words) | (100 * F.col("n_repeat_words") > max_repeat_percent * F.col("n_words"))
    lost = F.coalesce(F.col("removed_chars"), F.lit(0).cast("bigint"))
    depleted = lost > max_removed * F.col("line_chars")
    return joined.select(F.col("row").alias(id_col), "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"), lost.alias("removed_chars"), (~failed & ~depleted).alias("kept"))
