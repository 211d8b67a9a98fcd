import random

import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def corpus() -> list[tuple]:
    """Invented rows: copies, near copies, shared passages, junk, null and empty texts, repeated rows, one long text."""
    rng = random.Random(4)
    words = ["".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 7))) for _ in range(400)]
    say = lambda n: " ".join(rng.choice(words) for _ in range(n))
    passage, texts = say(70), [say(rng.randint(1, 120)) for _ in range(60)]
    texts += [texts[3], texts[3].upper(), texts[3], texts[5], passage, say(30) + " " + passage + " " + say(20), passage + "\n" + say(9), "", None, " \t\n", "äöü ß " * 60, "The The The The " * 40]
    texts += ["ab" * 300, "xab" + "ab" * 200, say(30_000), texts[10] + " tail", texts[10] + " Tail", "Ünï <|endoftext|> it's 12,5 ,. x"]
    rows = [(i, t, "en" if i % 3 else "fr", f"src{i % 4 if i % 2 else 0}", None if t is None else len(t)) for i, t in enumerate(texts)]
    rows += [rows[2], rows[2], (900, None, None, None, None), (901, "Abc", None, "src1", 3), (901, "other text here", "en", None, 15)]
    rows += [(None, "Abc", "en", "src1", 3), (None, texts[20], "en", "src2", 9), (None, texts[20] + " and more", None, "src2", 9), (None, passage, "fr", "src3", 7)]
    return rows


@pytest.fixture(scope="session")
def rows():
    return corpus()


@pytest.fixture(scope="session")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(3)


@pytest.fixture(scope="session")
def nothing(spark):
    return spark.createDataFrame([], SCHEMA)
