import random

import pytest

KIND = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def prose(rng, n, vocabulary=4000):
    return " ".join(f"w{rng.randrange(vocabulary)}x{rng.randrange(3)}" for _ in range(n))


@pytest.fixture(scope="session")
def rows():
    """Documents with nulls, empty and long texts, repeats, near copies and shared passages."""
    rng = random.Random(11)
    passage, base = prose(rng, 60), prose(rng, 120)
    texts = [prose(rng, rng.randrange(1, 150)) for _ in range(60)]
    texts += [None, "", "   \t\n", "one", "two words", "Ünïcödé ßtraße ÉCOLE", "a\x00b <|endoftext|> don't   stop now 12345", "\U0001f600 emoji ſ ﬁ"]
    texts += [texts[0], texts[0], texts[1] + " tail", base]
    for k in range(25):  # near copies of one text, each with its own change
        w = base.split()
        w[(5 * k) % 120] = f"changed{k}"
        texts.append(" ".join(w))
    texts += [prose(rng, 30) + "\n" + passage + "\t" + prose(rng, 20) for _ in range(6)]
    texts += [passage + " " + passage, passage, prose(rng, 3000, 200000), ("same " * 400).strip(), "x" * 200_000]
    order = list(range(len(texts)))
    rng.shuffle(order)
    langs = ["en", "fr", None]
    return [(i * 3 - 20, texts[k], langs[k % 3], f"s{k % 4}", len(texts[k] or "")) for i, k in enumerate(order)]


@pytest.fixture(scope="session")
def docs(spark, rows):
    return spark.createDataFrame(rows, KIND).repartition(3)


@pytest.fixture(scope="session")
def clashing(docs):
    """Extra columns under names that the operators use within."""
    from pyspark.sql import functions as F

    names = ["id", "block", "part", "rows", "n", "keys", "label", "a", "b", "bucket", "ghost", "ids", "body", "train", "signature", "size", "start", "row", "_id", "_text", "score", "lang_pred", "cross_entropy", "accepted", "kept", "n_words", "n_removed", "removed", "spans", "items", "key", "words", "order", "to", "top"]
    return docs.select("*", *[F.lit(n).alias(n) for n in names])


@pytest.fixture(scope="session")
def nothing(spark):
    return spark.createDataFrame([], KIND)
