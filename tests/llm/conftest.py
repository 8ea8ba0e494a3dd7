import random

import pytest

VOCAB = ["lorem", "ipsum", "Dolor", "sit", "amet,", "cön", "sect", "12", "e$", "!!", "x", "don't"]


def words_of(rng, n):
    return " ".join(rng.choice(VOCAB) for _ in range(n))


def make_rows():
    """Texts with nulls, empties, white space of all kinds, copies, near copies, shared passages and a long one."""
    rng = random.Random(5)
    wide = lambda n: " ".join(f"{rng.choice(VOCAB)}{rng.randrange(4000)}" for _ in range(n))
    rows = [(0, None), (1, ""), (2, " \t\n\x0b\x0c\r"), (3, "one"), (4, "two words"), (5, "a b c d e"), (6, "a b c d e")]
    base = wide(120)
    passage = wide(35)
    for i in range(7, 20):
        w = base.split()
        if i > 9:
            w[i * 3 % 100] = f"changed{i}"
        rows.append((i, " ".join(w)))
    for i in range(20, 40):
        rows.append((i, wide(rng.randint(1, 60)) + "\n" + passage + "\n" + wide(rng.randint(0, 60))))
    for i in range(40, 70):
        rows.append((i, "\n".join(words_of(rng, rng.randint(0, 12)) for _ in range(rng.randint(1, 9)))))
    rows.append((70, wide(6000)))
    rows.append((71, "é" * 50 + " <|endoftext|> " + "中文 ٣½ 'sa it's"))
    rows.append((72, "͸ unassigned " + wide(30)))
    rows += [(1000 - i, wide(rng.randint(1, 300))) for i in range(40)]
    return rows


@pytest.fixture(scope="session")
def rows():
    return make_rows()


@pytest.fixture(scope="session")
def docs(spark, rows):
    from pyspark.sql import functions as F

    df = spark.createDataFrame([(i, t, f"h{i % 3}" if i % 7 else None, len(t or "")) for i, t in rows], "doc_id long, text string, source string, n_chars long").repartition(3)
    # names that operators use themselves must not matter
    for name in ("kept", "score", "rep", "bucket", "_t", "lines", "n_words"):
        df = df.withColumn(name, F.lit("clash"))
    return df


@pytest.fixture(scope="session")
def empty(docs):
    return docs.limit(0)
