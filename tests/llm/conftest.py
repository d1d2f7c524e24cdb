import random

import pytest

#: Extra columns whose names the operators use inside.
CLASHES = "doc_id long, text string, lang string, source string, n_chars long, t1 long, size long, severity double, h string"


def words(rng, n, kinds=400):
    return [f"w{rng.randrange(kinds)}" for _ in range(n)]


def edge_texts():
    """Texts with nulls, empties, copies, near copies, shared passages, periodic and very long ones."""
    rng = random.Random(5)
    passage = " ".join(words(rng, 90))
    out = [None, "", " \t\n", "one", "one", "two words"]
    for _ in range(12):
        w = words(rng, rng.randint(40, 200))
        out.append(" ".join(w))
        if rng.random() < 0.5:
            out.append(" ".join(w))
        v = list(w)
        v[len(v) // 2] = "changed"
        out.append(" ".join(v))
        out.append(" ".join(w[:20]) + "\n" + passage + "  " + " ".join(words(rng, 30)))
    out += ["again and again " * 60, "a" * 1500, "é" * 700 + "x" + "é" * 700, "日本語のテキスト " * 80, " ".join(words(rng, 20_000, 100_000))]
    return out


@pytest.fixture(scope="session")
def rows():
    t = edge_texts()
    langs = ["en", "fr", None]
    out = [(i, x, langs[i % 3], f"s{i % 4}" if i % 5 else None, len(x or ""), i, i % 7, 0.5, "h") for i, x in enumerate(t)]
    return [*out, out[7], out[7], (None, t[8], "en", "s1", 3, 1, 1, 0.0, "h")]  # repeated rows and a null id


@pytest.fixture(scope="session")
def docs(spark, rows):
    return spark.createDataFrame(rows, CLASHES).repartition(5).cache()


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], CLASHES)
