import random
import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parent))

WORDS = {"en": "the of and to in is that it for was on with as his they at be this from have or by one had not but what all were when".split(), "xx": "zuq vexi orbo kali mund torv gesch wirr plok dran quell fjord yst abba cenn".split()}


def prose(rng, lang="en", n=40):
    return " ".join(rng.choice(WORDS[lang]) + rng.choice(["", "", "", ",", "."]) for _ in range(n))


SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def make_rows(seed=1, n=60):
    """Prose in two languages with copies, near copies, shared passages, junk, an empty, a null and a long text."""
    rng = random.Random(seed)
    rows = []
    passage = prose(rng, n=60)
    for i in range(n):
        lang = "en" if i % 3 else "xx"
        t = "\n".join(prose(rng, lang, rng.randrange(5, 40)) for _ in range(rng.randrange(1, 6)))
        if i % 5 == 0:
            t += "\n" + passage + "\n" + prose(rng, lang, 30)
        rows.append([i, t, lang])
    for i in range(n, n + 12):
        base = rows[rng.randrange(n // 3)][1].split(" ")
        if i % 2:
            base[rng.randrange(len(base))] = "changed"
        rows.append([i, " ".join(base), "en"])
    rows += [[n + 12, "", "en"], [n + 13, None, None], [n + 14, "   \n\t ", "xx"], [n + 15, "a", None], [n + 16, "ab " * 300, "en"], [n + 17, prose(rng, n=4000), "en"], [n + 18, "1234 5678 !!", "en"], [n + 19, "é ü ñ ß " * 20, "xx"]]
    return [(i, t, lang, None if i == 3 else f"src{0 if i % 3 else i % 4}", len(t or "")) for i, t, lang in rows]


@pytest.fixture(scope="session")
def rows():
    return make_rows()


@pytest.fixture(scope="session")
def docs(spark, rows):
    """Extra columns with names the operators use themselves."""
    from pyspark.sql import functions as F

    df = spark.createDataFrame(rows, SCHEMA).repartition(3)
    return df.withColumns({"d": F.lit("x"), "th": F.lit(1), "score": F.lit(9), "rep": F.lit(0), "v": F.lit(2), "kept": F.lit(False), "mix_key": F.lit("k"), "start": F.lit(1), "_mix_q": F.lit(1), "q_letters": F.lit(0.0), "_ld_d": F.lit(3), "ld_spans": F.lit(4), "_gone_id": F.lit(5), "predicted": F.lit(0), "sk": F.lit(6), "blk": F.lit(7)})


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)
