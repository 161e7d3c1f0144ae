import functools
import random
import re
from collections import Counter

from pyspark.sql import functions as F

from keyhop.llm.decontamination import bag_similarity, blocks, decontaminate, leaks, listed_values, simhash
from keyhop.llm.quality_rules import apply_rules

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def test_counts_equal_brute_force(docs, texts):
    rows = {r["doc_id"]: r for r in apply_rules(docs).collect()}
    for i, t in enumerate(texts):
        t = t or ""
        words = WORD.findall(t)
        windows = {}
        for k in range(len(words) - 4):
            windows.setdefault(tuple(words[k : k + 5]), []).append(k)
        repeat = {p for at in windows.values() if len(at) > 1 for a in at for p in range(a, a + 5)}
        lines = [x for x in t.split("\n") if WORD.search(x)]
        r = rows[i]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(repeat))
        assert r["base_failed"] == (len(words) < 10 or 100 * len(repeat) > 20 * len(words))
        assert r["kept"] <= (not r["base_failed"])


def test_frequent_lines_deplete_documents(spark):
    letters = lambda i: "".join("abcdefghij"[int(c)] for c in str(i))
    own = lambda i: " ".join(f"word{letters(i)}x{letters(k)}" for k in range(15))
    line = "this very line stands on every page of the host and on no other, navigation and all"
    rows = [(i, f"{line}\n{own(i)}\n{own(i + 1000)}", "a") for i in range(30)] + [(100 + i, f"{line} {i}\n{line} 2\nfew words", "a") for i in range(30)] + [(200 + i, line, "b") for i in range(5)]
    got = {r["doc_id"]: r["kept"] for r in apply_rules(spark.createDataFrame(rows, "doc_id bigint, text string, source string"), min_documents=20).collect()}
    assert all(got[i] for i in range(30))  # most of the text is their own
    assert not any(got[100 + i] for i in range(30))  # little is left (digits are folded)
    assert all(got[200 + i] for i in range(5))  # not frequent on that host


def test_short_and_digit_heavy_lines_deplete_documents(spark):
    menu = "\n".join(["Home", "News", "About us", "Contact", "Shop", "Help", "Log in", "Jobs", "Terms", "FAQ", "x"])
    phones = "\n".join(f"{who} {'0123456789' * 6} or {'9876543210' * 3}" for who in ("office", "sales", "fax line", "night desk", "press"))
    own = lambda i: " ".join(f"word{chr(97 + i)}x{chr(97 + k)}" for k in range(15))
    rows = [(i, menu, "a") for i in range(21)] + [(100 + i, phones, "a") for i in range(21)] + [(200 + i, f"{menu}\n \t\n{own(i)}\n{own(i + 1)}", "a") for i in range(8)] + [(300, menu, "b")]
    got = {r["doc_id"]: r for r in apply_rules(spark.createDataFrame(rows, "doc_id bigint, text string, source string"), min_documents=20).collect()}
    assert not any(r["base_failed"] for r in got.values())
    assert {i for i, r in got.items() if r["kept"]} == {*range(200, 208), 300}
    assert got[0]["removed_chars"] == len(menu.replace("\n", "")) and got[100]["removed_chars"] == len(phones.replace("\n", "")) and got[300]["removed_chars"] == 0


def test_rules_on_odd_rows(odd):
    rows = apply_rules(odd).collect()
    assert len(rows) == 4 and {r["n_words"] for r in rows if r["doc_id"] == 2} == {0}
    assert apply_rules(odd.limit(0)).count() == 0


def bag(words):
    return Counter(tuple(words[k : k + 5]) for k in range(len(words) - 4)) if len(words) >= 5 else Counter([tuple(words)] if words else [])


def test_leaks_equal_brute_force(spark, docs, texts):
    norm = lambda t: re.findall(r"[^\W_]+", (t or "").lower())
    edited = norm(texts[8])[:60]
    edited[30] = "changed"
    items = [(0, texts[10]), (1, " ".join(edited)), (2, "one two"), (3, None), (4, ""), (5, "nothing of this is anywhere in the documents at all"), (6, (texts[12] or "")[:200].upper() + "!!")]
    bench = spark.createDataFrame(items, "item_id bigint, text string")
    want = {}
    for d, t in enumerate(texts):
        words = norm(t)
        for i, x in items:
            item = norm(x)
            if not item:
                continue
            best = max((sum((bag(words[s : s + len(item)]) & bag(item)).values()) / sum((bag(words[s : s + len(item)]) | bag(item)).values()) for s in range(max(1, len(words) - len(item) + 1))), default=0)
            if best >= 0.8:
                want[d, i] = best
    got = {(r["doc_id"], r["item_id"]): r["similarity"] for r in leaks(docs, bench).collect()}
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-9 for k in want)
    assert {r["doc_id"] for r in decontaminate(docs, bench).select("doc_id").collect()} == set(range(len(texts))) - {d for d, _ in want}


def test_leaks_on_odd_rows(spark, odd):
    bench = spark.createDataFrame([(0, "twice the same"), (1, "some words of a text that has no id at all")], "item_id bigint, text string")
    assert {(r["doc_id"], r["item_id"]) for r in leaks(odd, bench).collect()} == {(1, 0), (None, 1)}
    assert leaks(odd.limit(0), bench).count() == 0 and leaks(odd, bench.limit(0)).count() == 0


def test_bag_similarity_counts_multiplicities(spark):
    rng = random.Random(4)
    rows = [([rng.randint(0, 5) for _ in range(rng.randint(0, 9))], [rng.randint(0, 5) for _ in range(rng.randint(0, 9))]) for _ in range(200)]
    got = spark.createDataFrame(rows, "a array<bigint>, b array<bigint>").select("a", "b", bag_similarity(F.col("a"), F.col("b")).alias("s")).collect()
    for r in got:
        a, b = Counter(r["a"]), Counter(r["b"])
        assert abs(r["s"] - ((a & b).total() / (a | b).total() if a or b else 0)) < 1e-12


def test_index_finds_all_fingerprints_within_the_radius(spark):
    rng = random.Random(6)
    pairs = []
    for _ in range(2000):
        x = rng.getrandbits(64)
        y = x
        for bit in rng.sample(range(64), rng.randint(0, 20)):
            y ^= 1 << bit
        pairs.append(tuple(v - (v >> 63 << 64) for v in (x, y)))
    df = spark.createDataFrame(pairs, "x bigint, y bigint")
    listed = [F.array_contains(listed_values(a, 20), b) for a, b in zip(blocks(F.col("x")), blocks(F.col("y")), strict=True)]
    assert df.where(functools.reduce(lambda p, q: p | q, listed)).count() == len(pairs)


def test_recall_of_edited_passages(spark):
    """Items of all sizes, each with as many words changed at an end as the similarity allows: the radius loses none of them."""
    rng = random.Random(8)
    words = [f"{a}{b}{c}" for a in "bdfgk" for b in "aeiou" for c in "lmnrst"]
    items, docs = [], []
    for i in range(300):
        item = [rng.choice(words) for _ in range(rng.randint(12, 80))]
        n = len(item) - 4
        cut = max(k for k in range(n) if n - k >= 0.8 * (n + k))
        held = [rng.choice(words) + "x" for _ in range(cut)] + item[cut:] if i % 2 else item[: len(item) - cut] + [rng.choice(words) + "x" for _ in range(cut)]
        items.append((i, " ".join(item)))
        docs.append((i, " ".join([rng.choice(words) for _ in range(30)] + held + [rng.choice(words) for _ in range(30)])))
    found = leaks(spark.createDataFrame(docs, "doc_id bigint, text string"), spark.createDataFrame(items, "item_id bigint, text string")).where("doc_id = item_id").collect()
    assert len(found) >= 0.99 * len(items) and min(r["similarity"] for r in found) < 0.82


def test_leaks_of_equal_windows_clashing_names_and_long_texts(spark):
    passage = "alpha beta gamma delta epsilon zeta eta theta"
    long = " ".join(f"w{i}" for i in range(60_000))
    rows = [(1, f"{passage} or {passage}", 5, "a"), (2, f"{long} {passage}", 6, "b"), (3, "clean words only", 7, "c")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, leaked int, item string").withColumns({"start": F.lit(1), "n": F.lit(2), "words": F.lit("x")})
    bench = spark.createDataFrame([(0, passage, 1)], "item_id bigint, text string, doc_id int")
    assert [(r["doc_id"], r["start_word"], r["similarity"]) for r in leaks(df, bench).orderBy("doc_id").collect()] == [(1, 0, 1.0), (2, 60_000, 1.0)]
    kept = decontaminate(df, bench)
    assert kept.columns == df.columns and [r["doc_id"] for r in kept.collect()] == [3]


def test_native_plans(docs):
    for df in (apply_rules(docs), leaks(docs, docs.select(F.col("doc_id").alias("item_id"), "text").limit(3))):
        assert not re.search("Python|Pandas|Arrow", df._jdf.queryExecution().toString())


def test_simhash_is_a_majority_of_bits(spark):
    same, other = spark.createDataFrame([(["a", "b", "c"],), (["c", "a", "b"],)], "w array<string>").select(simhash(F.col("w")).alias("h")).collect()
    assert same["h"] == other["h"]
