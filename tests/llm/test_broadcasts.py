"""What grows with the input is not sent to the driver, whatever size the planner takes it for."""

import random

import pytest
from pyspark.sql import DataFrame

from tmotif.llm import common, exact, quality, simhash


@pytest.fixture
def plans(monkeypatch):
    """The texts of the plans behind all tables that are staged."""
    kept: list[str] = []

    def staged(df: DataFrame, label: str, real=common.staged) -> DataFrame:
        kept.append(df._jdf.queryExecution().executedPlan().toString())
        return real(df, label)

    for module in (common, exact, quality, simhash):
        monkeypatch.setattr(module, "staged", staged)
    return kept


def test_near_copies_are_not_broadcast(spark, plans):
    rnd = random.Random(3)
    rows = [(d, " ".join(f"v{rnd.randrange(40)}" for _ in range(rnd.randint(1, 90)))) for d in range(200)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    assert simhash.drop_near_copies(df).count()
    sent = [line for text in plans for line in text.splitlines() if "BroadcastExchange" in line]
    assert len(plans) > 8 and not [x for x in plans if "SortMergeJoin" in x and "BroadcastExchange" in x] and len(sent) <= 2


def test_tables_of_the_classifier_are_not_broadcast(spark, plans):
    texts = spark.createDataFrame([("en", f"some words number {k}") for k in range(40)], "lang string, text string")
    quality.tables(quality.count_grams(texts, 3), 3).count()
    high = [x for x in plans if "SortMergeJoin" in x]
    assert len(high) == 3 and sum(x.count("SortMergeJoin") for x in high) >= 5


def test_marked_rows(spark, monkeypatch):
    """Row numbers as words of bits: the same rows as a list of numbers, over parts of files and the sign bit of a word."""
    rows = [k + (part << 33) for part in (0, 1, 7) for k in range(200)]
    some = [r for k, r in enumerate(rows) if k % 3 == 0 or (r & 63) in (0, 63)]
    df, numbers = (spark.createDataFrame([(r,) for r in x], "row bigint") for x in (rows, some + some[:5]))
    for most in (500_000, 1):
        monkeypatch.setattr(common, "BROADCAST_ROWS", most)
        out = common.marked(df, numbers)
        assert {r["row"] for r in out.where("marked").collect()} == {*some} and out.count() == len(rows)
    words = out._jdf.queryExecution().optimizedPlan().toString()
    assert "strategy=merge" in words
    none = common.marked(df, numbers.where("false"))
    assert none.where("not marked").count() == len(rows)
