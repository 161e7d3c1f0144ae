"""Near-duplicates by bottom-k sketches from one hash function.

Texts with the same set of shingles form a class, represented by its smallest id; from there on only
representatives take part. A representative's sketch holds its ``K`` smallest shingle hashes (all of
them in a set of at most ``K``). Inverted lists are kept of runs of neighbouring retained values: two
sets of Jaccard similarity 0.8 share four of five values of their common sketch, hence some run of
three neighbours, for sets within the sketch by counting and for larger ones with a probability of
missing of about 1e-10; single values, the most frequent ones above all, would make lists of
unrelated texts. Overlapping pairs of sets within the sketch are decided by their sketches, which are the
sets; others pass a filter by the similarity estimated from the union's sketch, and what passes is
verified on the full sets.

Large groups never become all their pairs. First every list is compared with its smallest member only;
what is linked becomes one component. Then, for lists with several components left, the pairs across
components are compared where the list is short. The texts in what is left of long lists, which share
a frequent passage, get new lists by prefix filtering: with values ordered by rarity among them, two
linked sets share one of the first ninth of the smaller's and the first fifth of the larger's values,
and a passage that many share comes last.
Pairs within a component are never needed, as only reachability is asked for.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyhop.llm.components import components
from keyhop.llm.quality_rules import let
from keyhop.llm.sampling import fresh_name
from keyhop.runtime import Scratch

K = 64
RUN = 3
#: How far below the threshold the estimate from the union's sketch may be, in standard deviations.
DEVIATIONS = 6
#: Lists of up to so many members are compared pairwise; longer ones are split by prefix filtering.
SHORT = 48
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def folded_words(text: Column) -> Column:
    """Words (runs of anything but ASCII white space) with A-Z in lower case; a null text has none."""
    text = F.coalesce(text.cast("string"), F.lit(""))
    lower = F.when(F.octet_length(text) == F.length(text), F.lower(text)).otherwise(F.translate(text, _UPPER, _LOWER))
    return F.filter(F.split(lower, r"[ \t-\r]+"), lambda w: w != "")


def shingle_set(text: Column, width: int) -> Column:
    """Sorted distinct hashes of the ``width``-word shingles; of fewer words, of the whole sequence."""

    def of(ws: Column) -> Column:
        last = F.size(ws) - width
        windows = F.transform(F.sequence(F.lit(0), F.greatest(last, F.lit(0))), lambda i: F.xxhash64(*(F.get(ws, i + k) for k in range(width))))
        whole = F.array(F.xxhash64(ws))
        return F.when(F.size(ws) == 0, F.array().cast("array<bigint>")).when(last < 0, whole).otherwise(windows)

    return F.sort_array(F.array_distinct(let(folded_words(text), of)))


def run_keys(sketch: Column) -> Column:
    """Hashes of the runs of ``RUN`` neighbours in a sketch; of two neighbours in very small sets.

    Sets of up to six values give runs of two, those of five and more runs of three, so that any two
    sets of similar size have one length in common.
    """

    def runs(s: Column, length: int) -> Column:
        return F.transform(F.sequence(F.lit(0), F.size(s) - length), lambda i: F.xxhash64(F.lit(length), *(F.get(s, i + k) for k in range(length))))

    none = F.array().cast("array<bigint>")

    def of(s: Column) -> Column:
        short = F.when(F.size(s).between(2, 6), runs(s, 2)).otherwise(none)
        return F.concat(short, F.when(F.size(s) >= 5, runs(s, RUN)).otherwise(none))

    return let(sketch, of)


def similar_size(a: str, b: str, percent: int) -> Column:
    """Whether sets of these sizes can reach the similarity."""
    return 100 * F.least(F.col(a), F.col(b)) >= percent * F.greatest(F.col(a), F.col(b))


def estimate(sa: Column, sb: Column) -> Column:
    """Similarity estimated on the K smallest values of the union of two sketches."""

    def of(union: Column) -> Column:
        return F.size(F.array_intersect(F.array_intersect(sa, sb), union)) / F.size(union)

    return let(F.slice(F.sort_array(F.array_union(sa, sb)), 1, K), of)


#: Written lists (of ids, or of list keys with an id) counted to be at most this long are broadcast, which
#: takes about 70 bytes a row (34 MB measured near the limit); beyond it the join shuffles, and Spark can
#: split its skewed sides.
BROADCAST_ROWS = 500_000


def sized(rows: DataFrame) -> DataFrame:
    """A written list, marked for broadcast if it is short enough."""
    return F.broadcast(rows) if rows.count() <= BROADCAST_ROWS else rows


class Linker:
    """Verifies candidate pairs of representatives."""

    def __init__(self, docs: DataFrame, reps: DataFrame, scratch: Scratch, percent: int, width: int):
        self.docs, self.reps, self.scratch, self.percent, self.width = docs, reps, scratch, percent, width

    def sets(self, ids: DataFrame, label: str) -> DataFrame:
        """``id`` and ``values``, the full set, of the documents listed in ``ids`` (column ``id``)."""
        wanted = sized(self.scratch.save(ids.distinct(), f"{label}-wanted"))
        return self.scratch.save(self.docs.join(wanted, "id", "left_semi").select("id", shingle_set(F.col("text"), self.width).alias("values")), f"{label}-sets")

    def links(self, pairs: DataFrame, label: str) -> DataFrame:
        """Of ``pairs`` (``a`` < ``b``, distinct) those that are linked, confirmed on full sets."""
        pairs = self.scratch.save(pairs, f"{label}-candidates")
        ids = self.scratch.save(pairs.select(F.col("a").alias("rep")).union(pairs.select("b")).distinct(), f"{label}-ids")
        own = self.scratch.save(self.reps.join(sized(ids), "rep", "left_semi"), f"{label}-sketches")
        sketch = lambda side: own.select(F.col("rep").alias(side), F.col("n").alias(f"n{side}"), F.col("sketch").alias(f"s{side}"))
        known = pairs.join(sketch("a"), "a").join(sketch("b"), "b").where(similar_size("na", "nb", self.percent))
        share = self.percent / 100
        union = F.least("na", "nb") / share  # the largest that a linked pair can have; it is sampled without replacement
        deviation = F.sqrt(F.greatest(share * (1 - share) / K * (1 - (K - 1) / union), F.lit(0.0)))
        close = estimate(F.col("sa"), F.col("sb")) >= share - DEVIATIONS * deviation - 1e-9
        full = (F.col("na") <= K) & (F.col("nb") <= K)  # then both sketches are the sets
        linked = let(F.size(F.array_intersect("sa", "sb")), lambda inter: 100 * inter >= self.percent * (F.col("na") + F.col("nb") - inter))
        passed = known.where(F.when(full, linked).otherwise(close)).select("a", "b", "na", "nb")
        passed = self.scratch.save(passed, f"{label}-passed")
        exact = passed.where(full).select("a", "b")
        large = passed.where(~full)
        sets = self.sets(large.select(F.col("a").alias("id")).union(large.select("b")), label)
        of = lambda side: sets.select(F.col("id").alias(side), F.col("values").alias(f"v{side}"))
        both = large.select("a", "b").join(of("a"), "a").join(of("b"), "b")
        inter = F.size(F.array_intersect("va", "vb"))
        sure = both.withColumn("inter", inter).where(100 * F.col("inter") >= self.percent * (F.size("va") + F.size("vb") - F.col("inter"))).select("a", "b")
        return self.scratch.save(exact.union(sure).distinct(), f"{label}-links")


def _placed(listed: DataFrame, groups: DataFrame | None) -> DataFrame:
    """With column ``component``: that of ``groups``, or the representative itself."""
    if groups is None:
        return listed.withColumn("component", F.col("rep"))
    return listed.join(groups.withColumnRenamed("node", "rep"), "rep", "left").withColumn("component", F.coalesce("component", "rep"))


def _merged(groups: DataFrame | None, links: DataFrame, scratch: Scratch, label: str) -> DataFrame:
    """``groups`` (``node``, ``component``) after adding ``links``."""
    if groups is None:
        return scratch.save(components(links, scratch, label), f"{label}-groups")
    named = groups.select(F.col("node").alias("rep"), F.col("component").alias("c"))
    ends = links.join(named.withColumnsRenamed({"rep": "a", "c": "ca"}), "a", "left").join(named.withColumnsRenamed({"rep": "b", "c": "cb"}), "b", "left")
    ends = scratch.save(ends.select("a", "b", F.coalesce("ca", "a").alias("ca"), F.coalesce("cb", "b").alias("cb")), f"{label}-ends")
    above = scratch.save(components(ends.select(F.col("ca").alias("a"), F.col("cb").alias("b")), scratch, label), f"{label}-above")
    up = above.select(F.col("node").alias("c"), F.col("component").alias("top"))
    both = groups.select("node", F.col("component").alias("c")).union(ends.select("a", "ca")).union(ends.select("b", "cb")).distinct()
    return scratch.save(both.join(up, "c", "left").select("node", F.coalesce("top", "c").alias("component")), f"{label}-groups")


def _compare(keyed: DataFrame, groups: DataFrame | None, linker: Linker, scratch: Scratch, label: str, short: int | None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Compare what shares a list (``key``, ``rep``, ``n``): stars, then pairs across components.

    ``rest`` bounds what a set can share with another whose first common key this is; ``small`` marks
    the rows that can be the smaller set of a pair; without these columns nothing is bounded. Returns the components, the last links, and the ids (``rep``) in lists longer than ``short`` that
    still hold several components.
    """
    role = F.col("small") if "small" in keyed.columns else F.lit(True)
    heads = keyed.groupBy("key").agg(F.min(F.when(role, F.col("rep"))).alias("head"), F.min("rep").alias("first"), F.max("rep").alias("last")).where(F.col("head").isNotNull() & (F.col("first") < F.col("last")))
    # Written first: its aggregation doesn't tie the lists' rows to their keys' tasks, so a long list is not one task's.
    heads = scratch.save(heads.select("key", "head"), f"{label}-heads")
    listed = keyed.join(sized(heads), "key")
    if "small" not in keyed.columns:
        listed = listed.withColumns({"rest": F.col("n"), "small": F.lit(True)})
    listed = scratch.save(listed, f"{label}-lists")
    stars = listed.where(F.col("rep") != F.col("head")).select(F.least("head", "rep").alias("a"), F.greatest("head", "rep").alias("b")).distinct()
    groups = _merged(groups, linker.links(stars, f"{label}-stars"), scratch, f"{label}-stars")
    placed = _placed(listed.where("rep <> head").select("key", "rep", "n", "rest", "small"), groups)
    open_keys = placed.groupBy("key").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.count(F.lit(1)).alias("many")).where("low < high").select("key", "many")
    open_keys = scratch.save(open_keys, f"{label}-open-keys")
    placed = scratch.save(placed.join(sized(open_keys), "key"), f"{label}-open")
    few = placed if short is None else placed.where(F.col("many") <= short)
    side = lambda x: few.select("key", "small", F.col("rep").alias(x), F.col("n").alias(f"{x}n"), F.col("rest").alias(f"{x}r"), F.col("component").alias(f"{x}c"))
    fits = (F.col("an") <= F.col("bn")) & similar_size("an", "bn", linker.percent) & ((100 + linker.percent) * F.least("ar", "br") >= linker.percent * (F.col("an") + F.col("bn")))
    across = side("a").where("small").drop("small").join(side("b").drop("small"), "key").where((F.col("a") != F.col("b")) & (F.col("ac") != F.col("bc")) & fits)
    across = across.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    links = linker.links(across, f"{label}-pairs")
    groups = _merged(groups, links, scratch, f"{label}-pairs")
    long = placed.where(F.lit(False)) if short is None else placed.where(F.col("many") > short)
    return groups, links, scratch.save(long.select("rep").distinct(), f"{label}-long")


def _rare_prefixes(ids: DataFrame, linker: Linker) -> DataFrame:
    """Lists (``key``, ``rep``, ``n``) of the rarest values of the full sets of ``ids``.

    Two linked sets, the smaller of size m, share at least 2p / (1 + p) of m and p of the larger's size,
    p being the similarity. In one order for all, by rarity, the first common value therefore stands
    among the first n - ceil(p n) + 1 of the larger and the first m - ceil(2p m / (1 + p)) + 1 of the
    smaller. From position i on a set of size n can share n - i values at most.
    """
    sets = linker.sets(ids.withColumnRenamed("rep", "id"), "rare").withColumnRenamed("id", "rep")
    values = sets.select("rep", F.size("values").cast("bigint").alias("n"), F.explode("values").alias("value"))
    counts = values.groupBy("value").agg(F.count(F.lit(1)).alias("many"))
    ranked = values.join(counts, "value").groupBy("rep", "n").agg(F.sort_array(F.collect_list(F.struct("many", "value"))).alias("order"))  # at most a text's own shingles
    prefix = F.col("n") - F.ceil(F.col("n") * linker.percent / 100) + 1
    placed = ranked.select("rep", "n", F.posexplode(F.slice("order", 1, prefix.cast("int"))).alias("at", "x")).where("x.many > 1")
    small = F.col("at") < F.col("n") - F.ceil(F.col("n") * 2 * linker.percent / (100 + linker.percent)) + 1
    return placed.select("rep", "n", F.col("x.value").alias("key"), (F.col("n") - F.col("at")).alias("rest"), small.alias("small"))


def near_duplicates(df: DataFrame, percent: int = 80, width: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col``, ``n_shingles``, ``component_id`` (smallest id reachable over links) and ``kept`` for every row.

    Two texts are linked where 100 * intersection >= ``percent`` * union of their shingle sets. A text
    without a word has an empty set and no link. Rows with equal ids but different texts are answered each
    by its own text. A row without an id is linked with nothing and kept. Texts are read whole at any
    length. Other columns are not read, whatever their names; an empty table gives an empty result. Of
    the intermediate tables two are left, which the result reads.
    """
    scratch = Scratch(df.sparkSession, "near-duplicates")
    docs = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    parsed = docs.select("id", shingle_set(F.col("text"), width).alias("values"))
    parsed = parsed.select("id", F.size("values").cast("bigint").alias("n"), F.xxhash64("values").alias("f1"), F.xxhash64(F.lit(1), "values").alias("f2"), F.slice("values", 1, K).alias("sketch"))
    parsed = scratch.save(parsed, "parsed")
    nonempty = parsed.where("n > 0 and id is not null")
    classes = scratch.save(nonempty.groupBy("f1", "f2", "n").agg(F.min("id").alias("rep")), "classes")
    named = classes.withColumnsRenamed({"f1": "g1", "f2": "g2", "n": "gn"})
    same = (F.col("f1") == F.col("g1")) & (F.col("f2") == F.col("g2")) & (F.col("n") == F.col("gn"))
    reps = nonempty.join(named, same & (F.col("id") == F.col("rep")), "left_semi").select(F.col("id").alias("rep"), "n", "sketch")
    reps = scratch.save(reps, "reps")
    linker = Linker(docs.where("id is not null"), reps, scratch, percent, width)

    keyed = reps.where("n >= 2").select("rep", "n", F.explode(run_keys(F.col("sketch"))).alias("key"))
    groups, links, long = _compare(keyed, None, linker, scratch, "runs", SHORT)
    if not long.isEmpty():
        groups, links, _ = _compare(_rare_prefixes(long, linker), groups, linker, scratch, "rare", None)

    final = named.join(groups, F.col("rep") == F.col("node"), "left").select("g1", "g2", "gn", F.coalesce("component", "rep").alias("component"))
    final = scratch.save(final, "final")
    scratch.keep("parsed", "final")
    out = parsed.drop("sketch").join(final, same & F.col("id").isNotNull(), "left")
    component = F.coalesce(F.col("component"), F.col("id"))
    return out.select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), component.alias("component_id"), F.coalesce(F.col("id") == component, F.lit(True)).alias("kept"))


def keep_one(docs: DataFrame, percent: int = 80, width: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` with one document left of each group of near-duplicates: that of the smallest id.

    Rows of one id are one document and stay or go together; rows without an id stay. Texts without a
    word are in no group. Columns of any name are kept, and an empty table stays empty.
    """
    dropped = fresh_name(docs, "dropped")
    found = near_duplicates(docs, percent, width, id_col, text_col).where("not kept").select(F.col(id_col).alias(dropped)).distinct()
    return docs.join(found, F.col(id_col) == F.col(dropped), "left_anti")
