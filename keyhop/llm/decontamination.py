"""Benchmark decontamination: SimHash of item-sized windows, Hamming blocks, exact verification.

Only DataFrame expressions. Windows have the sizes of benchmark items. A window can reach the
similarity only where it shares enough word shingles with some item of its size, so windows are cut
where a shared shingle says that they would start; nothing that could pass is left out by that, and no
item is chosen yet. Each window gets a 64-bit SimHash of its words, and the items of its size are found
by a multi-index: fingerprints are cut into ``BLOCKS`` blocks, and two within the radius differ in at
most radius / ``BLOCKS`` bits in some block. Items are listed under every block value that close to
their own, so one equi-join on (size, block number, block value) finds all pairs within the radius.
Each pair is then verified by the exact similarity of the two bags of shingles: the sum of the smaller
over the sum of the larger multiplicities.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyhop.llm.quality_rules import let
from keyhop.llm.sampling import fresh_name
from keyhop.runtime import Scratch

WIDTH = 5
BITS = 64
BLOCKS = 8


def normal_words(text: Column) -> Column:
    """Lower-case runs of letters and digits; a null text has none."""
    return F.filter(F.split(F.lower(F.coalesce(text.cast("string"), F.lit(""))), r"[^\p{L}\p{N}]+"), lambda w: w != "")


def shingles(words: Column, width: int) -> Column:
    """Hashes of the ``width``-word shingles at each position; none where there are fewer words."""

    def of(ws: Column) -> Column:
        last = F.size(ws) - width
        starts = F.when(last >= 0, F.sequence(F.lit(0), last)).otherwise(F.array().cast("array<int>"))
        return F.transform(starts, lambda i: F.xxhash64(F.lit(width), *(F.get(ws, i + k) for k in range(width))))

    return let(words, of)


def own_shingles(words: Column) -> Column:
    """Five-word shingles; of a shorter text, the whole sequence as one."""
    out = shingles(words, WIDTH)
    for width in range(WIDTH - 1, 0, -1):
        out = F.when(F.size(words) == width, shingles(words, width)).otherwise(out)
    return out


def simhash(words: Column) -> Column:
    """64-bit SimHash of a bag of words: a bit is set where more of the words' hashes have it set than not."""

    def bit(hs: Column, b: Column) -> Column:
        balance = F.aggregate(hs, F.lit(0), lambda s, h: s + F.when(F.call_function("getbit", h, b) == 1, 1).otherwise(-1))
        return F.when(balance > 0, F.call_function("shiftleft", F.lit(1).cast("bigint"), b)).otherwise(F.lit(0).cast("bigint"))

    return let(F.transform(words, lambda w: F.xxhash64(w)), lambda hs: F.aggregate(F.sequence(F.lit(0), F.lit(BITS - 1)), F.lit(0).cast("bigint"), lambda f, b: f.bitwiseOR(bit(hs, b))))


def blocks(fingerprint: Column) -> list[Column]:
    """The fingerprint cut into ``BLOCKS`` values."""
    width = BITS // BLOCKS
    return [F.shiftrightunsigned(fingerprint, k * width).bitwiseAND(F.lit((1 << width) - 1)) for k in range(BLOCKS)]


def block_radius(radius: int) -> int:
    """In some block two fingerprints within ``radius`` differ in at most so many bits."""
    return radius // BLOCKS


def listed_values(value: Column, radius: int) -> Column:
    """All block values that differ from ``value`` in at most ``block_radius(radius)`` bits."""
    masks = [m for m in range(1 << (BITS // BLOCKS)) if m.bit_count() <= block_radius(radius)]
    return F.transform(F.array(*(F.lit(m).cast("bigint") for m in masks)), lambda m: value.bitwiseXOR(m))


def bag_similarity(a: Column, b: Column) -> Column:
    """Sum of the smaller over sum of the larger multiplicities of two arrays' values; 0 for two empty ones.

    Two sorted arrays are merged once, so time is linear in their sizes after sorting.
    """

    def step(at: Column, xs: Column, ys: Column) -> Column:
        x, y = F.get(xs, at["i"]), F.get(ys, at["j"])
        done = x.isNull() | y.isNull()
        same = (x == y) & ~done
        add = lambda name, when: (at[name] + F.when(when, 1).otherwise(0)).alias(name)
        return F.struct(add("i", ~done & (x <= y)), add("j", ~done & (y <= x)), add("common", same))

    def of(xs: Column, ys: Column) -> Column:
        start = F.struct(F.lit(0).alias("i"), F.lit(0).alias("j"), F.lit(0).alias("common"))
        steps = F.sequence(F.lit(1), F.size(xs) + F.size(ys))
        merged = F.aggregate(steps, start, lambda at, _: step(at, xs, ys), lambda at: at["common"])
        share = let(merged, lambda c: c / (F.size(xs) + F.size(ys) - c))
        return F.when(F.size(xs) + F.size(ys) > 0, share).otherwise(F.lit(0.0))

    return let(F.sort_array(a), lambda xs: let(F.sort_array(b), lambda ys: of(xs, ys)))


def leaks(
    docs: DataFrame, benchmark: DataFrame, threshold: float = 0.8, radius: int = 20, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", broadcast_rows: int = 1_000_000, broadcast_documents: int = 50_000
) -> DataFrame:
    """A row for each document and benchmark item that it holds: the best window.

    Columns: id, item, ``start_word``, ``n_words``, ``hamming``, ``similarity`` (at least ``threshold``).
    Among equally similar windows the first is given. Words are runs of letters and digits, case
    folded, so punctuation and line breaks don't matter. Null texts and texts without words hold
    nothing and are held by nothing. Texts are read whole at any length. Rows with equal ids count as
    one document; a null id is an id like others. Other columns aren't read, whatever their names; an
    empty table of either kind gives an empty result. The items' shingles, their index (``BLOCKS`` rows
    for each listed value) and the documents to look into are broadcast only where their rows were
    counted to be within the given bounds; beyond them the joins shuffle.

    A window of similarity 0.8 differs from its item in about a tenth of the words and so in about nine
    bits of 64, with a standard deviation below three; ``radius`` 20 leaves out one in ten thousand.
    """
    scratch = Scratch(docs.sparkSession, "decontamination")
    words = F.col("words")
    items = scratch.save(
        benchmark.select(F.col(item_col).alias("item"), normal_words(F.col(item_text_col)).alias("words"))
        .where(F.size("words") > 0)
        .select("item", F.size("words").alias("n"), own_shingles(words).alias("item_shingles"), simhash(words).alias("item_hash")),
        "items",
    )
    size = items.agg(F.sum(F.size("item_shingles")).alias("rows"), F.collect_set(F.least(F.col("n"), F.lit(WIDTH))).alias("widths")).first()
    small = (size["rows"] or 0) <= broadcast_rows
    anchors = items.select("item", "n", F.size("item_shingles").alias("need"), F.posexplode("item_shingles").alias("at", "h"))
    worded = docs.select(F.col(id_col).alias("doc"), normal_words(F.col(text_col)).alias("words"))
    hits = None
    for width in sorted(size["widths"]) or [WIDTH]:
        own = anchors.where(F.least(F.col("n"), F.lit(WIDTH)) == width)
        each = worded.select("doc", F.posexplode(shingles(words, width)).alias("pos", "h"))
        found = each.join(F.broadcast(own) if small else own, "h").select("doc", "item", "n", "need", "h", (F.col("pos") - F.col("at")).alias("start"))
        hits = found if hits is None else hits.unionByName(found)
    # Similarity s needs a share of at least s of the item's distinct shingles, wherever they stand.
    held = hits.groupBy("doc", "item", "n", "need").agg(F.collect_set("h").alias("hs"), F.collect_set("start").alias("starts"))
    distinct_need = items.select(F.col("item").alias("i"), F.size(F.array_distinct("item_shingles")).alias("distinct"), F.size("item_shingles").alias("all"))
    held = held.join(F.broadcast(distinct_need) if small else distinct_need, F.col("item") == F.col("i")).where(F.size("hs") >= F.ceil(threshold * F.col("need")) - (F.col("all") - F.col("distinct")))
    looks = scratch.save(held.select("doc", F.explode("starts").alias("start"), "n").groupBy(F.col("doc").alias("look_doc")).agg(F.collect_set(F.struct("start", "n")).alias("looks")), "looks")
    keyed = F.broadcast(looks) if looks.count() <= broadcast_documents else looks
    windows = (
        worded.join(keyed, F.col("doc").eqNullSafe(F.col("look_doc")))
        .select("doc", "words", F.explode("looks").alias("look"))
        .withColumn("start", F.greatest(F.lit(0), F.least(F.col("look.start"), F.size("words") - F.col("look.n"))))
        .select("doc", "start", F.col("look.n").alias("n"), F.slice("words", F.col("start") + 1, F.col("look.n")).alias("window"))
    )
    windows = scratch.save(windows.select("doc", "start", "n", own_shingles(F.col("window")).alias("window_shingles"), simhash(F.col("window")).alias("window_hash")), "windows")
    numbered = lambda values: F.posexplode(F.array(*values)).alias("block", "value")
    left = windows.select("doc", "start", "n", "window_shingles", "window_hash", numbered(blocks(F.col("window_hash"))))
    index = items.select("item", "n", "item_hash", numbered(blocks(F.col("item_hash")))).withColumn("value", F.explode(listed_values(F.col("value"), radius)))
    index_small = index.count() <= broadcast_rows
    pairs = left.join(F.broadcast(index) if index_small else index, ["n", "block", "value"])
    distance = F.bit_count(F.col("window_hash").bitwiseXOR(F.col("item_hash")))
    close = [F.bit_count(a.bitwiseXOR(b)) <= block_radius(radius) for a, b in zip(blocks(F.col("window_hash")), blocks(F.col("item_hash")), strict=True)]
    first_block = F.coalesce(*(F.when(same, F.lit(k)) for k, same in enumerate(close)))
    near = pairs.where((distance <= radius) & (F.col("block") == first_block))  # each pair once
    bags = items.select(F.col("item").alias("of_item"), F.col("n").alias("of_n"), F.col("item_hash").alias("of_hash"), "item_shingles").distinct()
    same_item = F.col("item").eqNullSafe(F.col("of_item")) & (F.col("n") == F.col("of_n")) & (F.col("item_hash") == F.col("of_hash"))
    near = near.join(F.broadcast(bags) if small else bags, same_item)
    near = near.withColumn("similarity", bag_similarity(F.col("window_shingles"), F.col("item_shingles"))).where(F.col("similarity") >= threshold)
    best = near.groupBy("doc", "item").agg(F.min(F.struct((-F.col("similarity")).alias("less"), F.col("start"), F.col("n"), distance.alias("hamming"))).alias("b"))
    return best.select(F.col("doc").alias(id_col), F.col("item").alias(item_col), F.col("b.start").cast("bigint").alias("start_word"), F.col("b.n").cast("bigint").alias("n_words"), F.col("b.hamming").cast("int").alias("hamming"), (-F.col("b.less")).alias("similarity"))


def decontaminate(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", **options) -> DataFrame:
    """The rows of ``docs`` that hold no benchmark item.

    Rows of one id stay or go together, a null id as any other. Columns of any name are kept.
    """
    leaked = fresh_name(docs, "leaked")
    found = leaks(docs, benchmark, id_col=id_col, **options).select(F.col(id_col).alias(leaked)).distinct()
    return docs.join(found, F.col(id_col).eqNullSafe(F.col(leaked)), "left_anti")
