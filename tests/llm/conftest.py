import random

import pytest

WORDS = ["ber", "than", "the", "of", "ing", "tion", "ou", "re", "é", "keit", "ción", "des", "un", "ar"]


def make_text(rng, words):
    return " ".join("".join(rng.choice(WORDS) for _ in range(rng.randint(1, 4))) for _ in range(words))


@pytest.fixture(scope="session")
def texts():
    """Documents with copies, near copies, edge cases; ids from 0, then a null id and a repeated row."""
    rng = random.Random(7)
    out = [make_text(rng, rng.randint(3, 200)) for _ in range(60)]
    out += [out[3], out[3], out[4] + " tail", out[5].upper(), "", None, "   \n\t ", "one", "one two", "ONE two", "a\x1cb c\x0bd", "x" * 5000 + " y", ("same five words again here " * 30).strip()]
    base = make_text(rng, 120).split()
    for k in range(20):
        own = list(base)
        own[rng.randrange(len(own))] = f"edit{k}"
        out.append(" ".join(own))
    passage = make_text(rng, 80)
    out += [passage + " " + make_text(rng, 14) for _ in range(25)]
    return out


@pytest.fixture(scope="session")
def docs(spark, texts):
    """The texts with columns whose names clash with those that operators use inside."""
    rows = [(i, t, ("en", "de", None)[i % 3], f"src{i % 2}" if i % 5 else None, len(t or ""), 1.0, "x", i) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint, score double, id string, row int").repartition(3)


@pytest.fixture(scope="session")
def odd(spark):
    """A null id, repeated rows, and nothing but nulls."""
    rows = [(None, "some words of a text that has no id at all but ten words", None, None, None), (1, "twice the same", "en", "s", 3), (1, "twice the same", "en", "s", 3), (2, None, None, None, None)]
    return spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
