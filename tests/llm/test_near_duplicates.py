import random
import re
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from keyhop.llm import near_duplicates as nd
from keyhop.llm.components import components
from keyhop.runtime import Scratch

WORD = re.compile(r"[^\x20\x09-\x0D]+")
FOLD = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def brute_force(texts, percent, width):
    sets = []
    for t in texts:
        w = WORD.findall((t or "").translate(FOLD))
        sets.append({tuple(w[k : k + width]) for k in range(len(w) - width + 1)} if len(w) >= width else {tuple(w)} if w else set())
    least = list(range(len(texts)))
    changed = True
    links = [(a, b) for a in range(len(sets)) for b in range(a) if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b])]
    while changed:
        changed = False
        for a, b in links:
            low = min(least[a], least[b])
            if (least[a], least[b]) != (low, low):
                least[a] = least[b] = low
                changed = True
    return sets, least


@pytest.mark.parametrize("width", [2, 5])
@pytest.mark.parametrize("short", [48, 3])
def test_components_equal_brute_force(docs, texts, width, short, monkeypatch):
    monkeypatch.setattr(nd, "SHORT", short)  # 3: long lists come into play
    sets, least = brute_force(texts, 80, width)
    rows = {r["doc_id"]: r for r in nd.near_duplicates(docs, 80, width).collect()}
    assert [rows[i]["n_shingles"] for i in range(len(texts))] == [len(s) for s in sets]
    assert [rows[i]["component_id"] for i in range(len(texts))] == least
    assert all(rows[i]["kept"] == (least[i] == i) for i in range(len(texts)))


def test_pairs_of_full_sketches_are_decided_exactly(spark):
    """Sets of 60 to 66 shingles, whose union exceeds the sketch, with as few common ones as a link needs, or one less."""
    texts = []
    for k in range(60):
        n, m = 60 + k % 7, 60 + k // 7 % 7
        common = -(-80 * (n + m) // 180) - k % 2  # 100 c >= 80 (n + m - c)
        words = [f"w{k}x{i}" for i in range(n + m - common)]
        texts += [" ".join(words[:n]), " ".join(words[n - common :])]
    sets, least = brute_force(texts, 80, 1)
    assert 20 < sum(c != i for i, c in enumerate(least)) < 40
    rows = {r["doc_id"]: r for r in nd.near_duplicates(spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string"), 80, 1).collect()}
    assert [rows[i]["component_id"] for i in range(len(texts))] == least


@pytest.mark.parametrize("width", [1, 5])
def test_recall_near_the_threshold(spark, width):
    """Pairs of sets of 55 to 900 shingles that just reach the similarity, or just don't: all decided as on full sets."""
    rng = random.Random(width)
    texts, want = [], []
    for k in range(240):
        n = rng.randint(55, 90) if k % 2 else rng.randint(100, 900)
        common = -(-80 * 2 * n // 180) - (k % 3 == 0)
        words = [f"w{k}x{i}" for i in range(2 * n - common + width - 1)]
        one, two = words[: n + width - 1], words[n - common :]
        texts += [" ".join(one), " ".join(two)]
        sets = [{tuple(t[i : i + width]) for i in range(len(t) - width + 1)} for t in (one, two)]
        want.append(100 * len(sets[0] & sets[1]) >= 80 * len(sets[0] | sets[1]))
    rows = {r["doc_id"]: r for r in nd.near_duplicates(spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string"), 80, width).collect()}
    assert [rows[2 * k + 1]["component_id"] == 2 * k for k in range(240)] == want and 100 < sum(want) < 200


def test_keep_one_with_clashing_names(spark):
    text = " ".join(f"word{i}" for i in range(40))
    rows = [(1, text, 0, 0), (2, text + " more", 0, 0), (3, "other words", 0, 0), (None, text, 0, 0), (4, None, 0, 0), (4, None, 0, 0)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, dropped int, component int").withColumns({"n": F.lit(1), "rep": F.lit(2), "key": F.lit(3), "values": F.lit(4)})
    kept = nd.keep_one(df)
    assert kept.columns == df.columns and sorted(r["doc_id"] or -1 for r in kept.collect()) == [-1, 1, 3, 4, 4]
    assert nd.keep_one(df.limit(0)).count() == 0


def test_odd_rows(odd):
    rows = nd.near_duplicates(odd).collect()
    assert sorted((r["doc_id"] or -1, r["component_id"] or -1, r["kept"]) for r in rows) == [(-1, -1, True), (1, 1, True), (1, 1, True), (2, 2, True)]
    assert nd.near_duplicates(odd.limit(0)).count() == 0


def test_components(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, k) for k in range(101, 140)] + [(200, 201)]
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(edges, "a bigint, b bigint"), Scratch(spark, "t"), "t").collect()}
    groups = defaultdict(set)
    for n, c in got.items():
        groups[c].add(n)
    assert groups == {0: set(range(41)), 100: set(range(100, 140)), 200: {200, 201}}
