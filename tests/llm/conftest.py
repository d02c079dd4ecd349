import random

import pytest

COLUMNS = "doc_id long, text string, lang string, source string, n_chars long"


def frame(spark, texts, extra=""):
    """Documents of these texts, numbered from 0."""
    rows = [(i, t, "en", "src0", None if t is None else len(t)) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, COLUMNS)


@pytest.fixture(scope="session")
def prose():
    """prose(n, seed): n invented words."""
    syllables = ["ta", "ri", "mo", "len", "dor", "ka", "vi", "sul", "pe", "nar", "gi", "tho"]

    def words(n, seed=0, vocabulary=5000):
        draw = random.Random(seed)
        return " ".join("".join(random.Random(draw.randrange(vocabulary)).choices(syllables, k=3)) for _ in range(n))

    return words


#: Texts that every operator must take.
ODD = [None, "", " \n\t ", "a", "the the the the", "x" * 5000, "é ü 漢字 \U0001f600", "a\x1cb", "<|endoftext|> it's", "tab\tand\x0bform\x0c"]
