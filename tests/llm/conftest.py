import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, kept string, id string, n_words string, score int"
WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon phi chi psi omega".split()


@pytest.fixture(scope="session")
def texts():
    """Ordinary, null, empty, blank, repeated and very long texts, with hot copies."""
    import random

    rng = random.Random(3)
    line = lambda n: " ".join(rng.choice(WORDS) + rng.choice(["", "", ",", "."]) for _ in range(n))
    base = line(60)
    shared = line(30)
    out = [None, "", " \t\n", "one", "Ünï cödé 東京 😀 word", line(3), base, base, base.upper()]
    out += [base.replace("alpha", "alfa", 1), base + " extra", line(40) + " " + shared, line(40) + " " + shared, shared]
    out += [line(rng.randint(5, 80)) for _ in range(20)]
    out += ["spam spam\n" * 40, "x" * 20_000, line(20_000), "The MIT License\n" + line(20), "Licensed under the Apache License, Version 2.0. " + line(10)]
    return out


@pytest.fixture(scope="session")
def rows(texts):
    out = [(i, t, ["en", "de", None][i % 3], ["hot", "hot", None, "src"][i % 4], len(t or ""), "x", "y", "z", 1) for i, t in enumerate(texts)]
    out.append((6, texts[6], "en", "hot", 1, "x", "y", "z", 1))  # a repeated row's id
    out.append((None, texts[6], None, None, None, None, None, None, None))
    return out


@pytest.fixture(scope="session")
def docs(spark, rows):
    df = spark.createDataFrame(rows, SCHEMA).repartition(3).persist()
    df.count()
    return df


@pytest.fixture(scope="session")
def empty(docs):
    return docs.filter("false")
