import random

import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, digest string, size int, run int, best string, t string, a int, text_crc32 string, words int"


def texts() -> list[tuple]:
    r = random.Random(5)
    w = ["".join(r.choice("abcdeé") for _ in range(r.randint(1, 7))) for _ in range(300)]
    body = [" ".join(r.choice(w) for _ in range(n)) for n in (1, 2, 3, 5, 30, 80, 200, 700)]
    rows = [(i, t) for i, t in enumerate(body)]
    rows += [(20, body[5]), (21, body[5] + "  "), (22, "\t" + body[5].replace(" ", "\n")), (23, body[6].upper())]
    rows += [(30, None), (31, ""), (32, " \n\t "), (33, " "), (34, "x" * 30_000), (35, "ab " * 20_000)]
    rows += [(40, body[4]), (40, body[4]), (40, "other text"), (None, body[4]), (None, None), (-7, "ß İ ǅ 😀 é"), (1 << 60, "end <|endoftext|> here")]
    rows += [(50, "two  spaces \n and\n\nlines.  Ends "), (51, " leads"), (52, "a's b'll  thin \x1f unit"), (53, body[7] + " x")]
    rows += [(60 + i, body[6] + f" tail{i}") for i in range(5)]
    return rows


def frame(spark, rows):
    return spark.createDataFrame([(i, t, None, "src0" if t else None, None, "d", 1, 2, None, "t", 3, "c", None) for i, t in rows], SCHEMA)


@pytest.fixture(scope="session")
def edge_rows():
    return texts()


@pytest.fixture(scope="session")
def edge(spark, edge_rows):
    return frame(spark, edge_rows).repartition(5)


@pytest.fixture(scope="session")
def empty(spark):
    return frame(spark, [])
