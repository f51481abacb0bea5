"""Hot dialogues and fingerprints under several salts, and the cases of perspective rotation."""

from __future__ import annotations

import duckdb
import pandas as pd
import pytest
from pyspark.sql import functions as F

from motif_spark.llm import chat, common, simhash

TURNS = "conv_id long, turn long, role string, text string"


@pytest.fixture(params=[10, 100_000])
def hot(request, monkeypatch):
    monkeypatch.setattr(common, "HOT_ROWS", request.param)
    monkeypatch.setattr(common, "HOT_SHARE", 0.01)


def table(rows: list[tuple]) -> list[tuple]:
    return sorted((tuple(str(None if x is None or x != x else int(x) if isinstance(x, float) else x) for x in r) for r in rows))


def test_rotation_of_hot_and_odd_dialogues(spark, hot):
    rows = [(1, k // 2, ("ann", "bob", "system")[k % 3], f"text {k % 7}") for k in range(120)]
    rows += [(2, None, ("ann", None)[k % 2], ("b", "a", "", None, "ab", "abc")[k % 6]) for k in range(60)]
    rows += [(None, k, "eve", "x" * (k % 4)) for k in range(40)] + [(3, 0, "system", "alone"), (4, 5, "ann", "y" * 30_000)] + [(5, 1, "zed", "same")] * 25
    rows += [(6, k % 9 - 5, ("ann", "anna")[k % 2], "aab"[: k % 4]) for k in range(45)]
    df = spark.createDataFrame(rows, TURNS)
    con = duckdb.connect()
    con.register("conversations", pd.DataFrame(rows, columns=["conv_id", "turn", "role", "text"]).astype({"conv_id": "Int64", "turn": "Int64"}))
    want = con.sql(chat.ROTATE_SQL)
    got = chat.rotate(df).select(*want.columns).collect()
    assert table([tuple(r) for r in got]) == table(want.fetchall())


def test_rotation_of_empty_and_clashing_tables(spark):
    assert chat.rotate(spark.createDataFrame([], TURNS)).count() == 0
    df = spark.createDataFrame([(1, 0, "ann", "hi"), (1, 0, "ann", "hi")], TURNS)
    for name in ("_head", "_block", "_salt", "_s", "perspective", "segment", "n", "start"):
        df = df.withColumn(name, F.lit("x"))
    assert chat.rotate(df).count() == 2


def test_components_of_hot_fingerprints(spark, hot):
    rows = [(k, "") for k in range(50)] + [(100 + k, "one two three four five") for k in range(40)] + [(300, "quite another text of words"), (None, "")]
    got = {r.doc_id: r.component_id for r in simhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert len(got) == len(rows)
    for i, text in rows:
        assert got[i] == (0 if text == "" else 100 if text.startswith("one") else 300)
