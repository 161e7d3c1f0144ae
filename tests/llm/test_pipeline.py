import re
from collections import Counter

import corpus_pipeline
from keyhop.llm import pii, quality_classifier
from keyhop.runtime import table
from pyspark.sql import functions as F

FOLD = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def smallest_of_groups(rows):
    """Ids that are the smallest of their groups of near-duplicates, by comparing all pairs."""
    sets = {}
    for i, text in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(FOLD))
        sets[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()
    least = {i: i for i in sets}

    def root(i):
        while least[i] != i:
            i = least[i]
        return i

    ids = sorted(sets)
    for n, a in enumerate(ids):
        for b in ids[n + 1 :]:
            x, y = sets[a], sets[b]
            if x and y and 100 * min(len(x), len(y)) >= 80 * max(len(x), len(y)) and 100 * len(x & y) >= 80 * len(x | y):
                low, high = sorted((root(a), root(b)))
                least[high] = low
    return {i for i in ids if root(i) == i}


def holding(rows, items):
    """Ids of texts with a window of an item's size whose bag of shingles is similar enough, by trying all windows."""
    bag = lambda ws: Counter(tuple(ws[k : k + 5]) for k in range(len(ws) - 4)) if len(ws) >= 5 else Counter([tuple(ws)] if ws else [])
    norm = lambda t: re.findall(r"[^\W_]+", (t or "").lower())
    out = set()
    wanted = [(w, bag(w)) for w in map(norm, items) if w]
    for i, text in rows:
        words = norm(text)
        whole = bag(words)
        for item, need in wanted:
            if len(item) >= 5 and sum((whole & need).values()) < 0.8 * sum(need.values()):
                continue  # no window can hold more
            windows = (bag(words[s : s + len(item)]) for s in range(max(1, len(words) - len(item) + 1)))
            if any((b & need).total() >= 0.8 * (b | need).total() for b in windows):
                out.add(i)
                break
    return out


def test_stages_over_the_small_tables(spark, sf, tmp_path):
    """Each stage's decision, recomputed from its operator on the stage's own input."""
    docs = table(spark, sf, "documents")
    seen = {}
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, docs, sf).write.parquet(str(tmp_path / name))
        out = spark.read.parquet(str(tmp_path / name))
        if name != "packing":
            assert out.columns == list(corpus_pipeline.COLUMNS)
        seen[name] = (docs, out)
        docs = out
    before, after = seen["quality_classifier"]
    model = quality_classifier.train(before, table(spark, sf, "labels"))
    good = {r["doc_id"] for r in quality_classifier.classify(before, model).where("predicted = 1").collect()}
    assert {r["doc_id"] for r in after.collect()} == good
    before, after = seen["near_duplicates"]
    assert {r["doc_id"] for r in after.collect()} == smallest_of_groups([(r["doc_id"], r["text"]) for r in before.collect()])
    before, after = seen["decontamination"]
    held = holding([(r["doc_id"], r["text"]) for r in before.collect()], [r["text"] for r in table(spark, sf, "benchmark").collect()])
    assert held and {r["doc_id"] for r in before.collect()} - {r["doc_id"] for r in after.collect()} == held
    before, after = seen["pii"]
    assert before.count() == after.count() and not any(pii.base_spans(r["text"]) for r in after.collect())
    before, pieces = seen["packing"]
    assert pieces.select("doc_id").distinct().count() == before.count()


def test_stages_on_odd_rows_and_clashing_names(spark, sf, odd):
    clashing = odd.withColumns({"dropped": F.lit(1), "leaked": F.lit(2), "score": F.lit(3), "predicted": F.lit(4), "words": F.lit("x"), "id": F.lit(5), "row": F.lit(6)})
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, clashing, sf)
        rows = out.collect()
        if name == "packing":
            assert len(rows) == 4
        else:
            assert out.columns == list(corpus_pipeline.COLUMNS) and (len(rows) == 4 or name == "quality_classifier")
        assert stage(spark, clashing.limit(0), sf).count() == 0
