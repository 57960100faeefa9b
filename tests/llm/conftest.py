import random

import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long, digest string, component long, rid long, size int, words string"


def frame(spark, rows):
    """Documents with further columns whose names clash with those inside the operators."""
    return spark.createDataFrame([(i, t, None if i is None else "en", None if i is None else f"s{i % 4}", len(t or ""), "x", 7, 1, 2, None) for i, t in rows], DOCS)


def corpus(n=60, seed=3):
    r = random.Random(seed)
    words = ["".join(r.choice("abcdeiostn") for _ in range(r.randint(1, 8))) for _ in range(900)]
    passage = " ".join(r.choice(words) for _ in range(40))
    rows = []
    for i in range(n):
        kind = i % 6
        body = [r.choice(words) for _ in range(r.randint(3, 160))]
        if kind == 1 and rows:
            body = rows[r.randrange(len(rows))][1].split(" ")
            for _ in range(max(1, len(body) // 60)):
                body[r.randrange(len(body))] = r.choice(words)
        if kind == 2:
            body[len(body) // 2 : len(body) // 2] = passage.split(" ")
        rows.append((i, rows[-1][1] if kind == 3 else " ".join(body)))
    rows += [(n, ""), (n + 1, None), (n + 2, "one two"), (n + 3, "One  TWO"), (n + 4, " \n\t "), (n + 5, "é" * 300), (n + 6, "ab" * 40_000), (n + 7, "ß̈ 日本語 \U0001f600 " * 30)]
    return rows


@pytest.fixture(scope="session")
def rows():
    return corpus()
