import hashlib
import random

import pytest

from avcurate.llm import queries


@pytest.fixture(scope="session")
def tokenizer():
    return queries.tokenizer


def words(rng: random.Random, n: int) -> str:
    return " ".join("".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 8))) for _ in range(n))


@pytest.fixture(scope="session")
def texts():
    """Texts with nulls, empty ones, white space, copies, near copies, shared passages and odd characters."""
    rng = random.Random(4)
    passage = words(rng, 120)
    base = [words(rng, rng.randint(1, 400)) for _ in range(30)]
    near = [base[3] + " " + words(rng, 1), base[3].replace("a", "b", 1), base[3]]
    shared = [words(rng, 40) + " " + passage + " " + words(rng, 30), passage + words(rng, 5), words(rng, 3) + passage]
    odd = [None, "", "   \n\t", "x", "é" * 700, "ab" * 900, "a<|endoftext|>b", "12 <|startoftext|> Σ ΑΣ it's", "\x1c\x85　z", "😀" * 50, "7 8 9 !?"]
    return base + near + shared + odd + [base[0], base[0]]


@pytest.fixture(scope="session")
def docs(spark, texts):
    rng = random.Random(9)
    langs = ["en", "de", None]
    rows = [(10 * i + 3, t, rng.choice(langs), "s", 0 if t is None else len(t), "extra", i) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, rid string, shard int").repartition(3).cache()


@pytest.fixture(scope="session")
def empty_docs(spark):
    return spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")


def sha(b: bytes) -> str:
    return hashlib.sha256(b).hexdigest()
