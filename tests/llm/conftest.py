import random

import pytest

COLUMNS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="session")
def docs(spark):
    """Odd rows among ordinary ones: nulls, blanks, repeats, copies, a long text, clashing extra columns."""
    rng = random.Random(3)
    vocabulary = ["".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 7))) for _ in range(400)]
    line = lambda n: " ".join(rng.choice(vocabulary) for _ in range(n))
    rows = [(i, "\n".join(line(rng.randint(5, 30)) for _ in range(rng.randint(1, 5))), rng.choice(["en", "de"])) for i in range(40)]
    passage = line(30)
    rows += [(100, rows[3][1], "en"), (101, rows[3][1] + " end", "de"), (102, line(9) + " " + passage + " " + line(7), "en"), (103, passage, None)]
    rows += [(200, None, "en"), (201, "", "de"), (202, "  \n\t ", None), (203, "☺ 123 🙂", "en"), (204, "word", "en"), (205, "Word", "de"), (206, "two words", "en")]
    rows += [(300, line(4000), "de"), (None, "no id here at all but text", "en"), (301, passage.upper() + "!", "en"), (301, passage.upper() + "!", "en")]
    rows += [(400, "same line for all\nsame line for all\nother " + line(4), "en"), (401, "same line for all", "de")]
    out = [(i, t, lang, "s", None if t is None else len(t)) for i, t, lang in rows]
    df = spark.createDataFrame(out, COLUMNS)
    return df.selectExpr("*", "'x' AS removed_lines", "1 AS rank", "2 AS fp", "3 AS _n", "4 AS token").repartition(4)


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], COLUMNS)


@pytest.fixture(scope="session")
def rows(docs):
    return [(r["doc_id"], r["text"]) for r in docs.collect()]
