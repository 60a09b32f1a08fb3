import os
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__)))))


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    made = SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    made.sparkContext.setLogLevel("ERROR")
    return made


AWKWARD = [
    (0, None), (1, ""), (2, "   \n\t "), (3, "one"), (4, "One two\tthree"), (5, "One two\tthree"),
    (6, "a  b  c <|endoftext|> d ▁ e"), (7, "日本語 テキスト ñandú É ﬁ"), (8, "word " * 20_000), (9, "x" * 9000),
    (10, "the cat sat on the mat and the dog sat on the log by the door today"), (11, "the cat sat on the mat and the dog sat on the log by the door today"),
    (12, "a\x00b \x0b c\r\nd"), (13, "Don't STOP!! it's 12.50 €\n\n\n"),
]


@pytest.fixture
def awkward(spark):
    rows = [(i, t, "en" if i % 3 else None, "s", 1, 2.0) for i, t in AWKWARD]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_tokens long, score double")
