import random
import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[2]))
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, block int, bucket int, label string, shard int, range int, w string"


def odd_rows() -> list[tuple]:
    """Nulls, empty and long texts, copies, near copies, repeated rows, a shared passage, low entropy."""
    rng = random.Random(5)
    words = ["".join(rng.choice("abcdefghij") for _ in range(rng.randint(1, 9))) for _ in range(300)]
    text = lambda n: " ".join(rng.choice(words) for _ in range(n))
    passage, base = text(15), text(120)
    near = base.split()
    near[60] = "changed"
    texts = [None, "", " ", "a", "a b c d", "A b C d", "é ü ß\nñ", base, base, " ".join(near), base + " tail", passage + " " + text(40), text(40) + " " + passage, text(30) + " " + passage + " " + text(30)]
    texts += ["aaaa" * 100, "aaaa" * 90, "ab " * 200, "日本語のテキスト" * 20, "x" * 49, "x" * 50, "line\nline\nline\nother " + text(30), text(6000), "word " * 3000, "\t\n\x0b\x0c\r", "Σίσυφος ΣΟΦΟΣ", "don't   stop now   ok"]
    texts += [text(rng.randint(1, 60)) for _ in range(30)]
    rows = [(i, t, None if i % 7 == 0 else "en", None if i % 5 == 0 else "s", 3, 1, 2, "x", 4, 5, "y") for i, t in enumerate(texts)]
    return [*rows, rows[7], rows[3], (None, base, None, None, None, None, None, None, None, None, None), (None, None, *[None] * 9)]


@pytest.fixture(scope="session")
def odd(spark):
    return spark.createDataFrame(odd_rows(), SCHEMA).repartition(3)


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)
