"""Near duplicates go by row: repeated rows, rows without an id, and different texts of one id."""

from __future__ import annotations

from stratastore.llm import near_dup


def test_one_row_of_each_class_stays(spark):
    a, b, c = ("alpha beta gamma delta epsilon zeta eta", "one two three four five six seven", "red green blue black white pink grey")
    rows = [(1, a), (2, a), (2, b), (3, c), (3, c), (None, "p q r s t u v"), (None, "p q r s t u v"), (None, ""), (9, None)]
    kept = near_dup.keep_one(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    want = [(1, a), (2, b), (3, c), (None, "p q r s t u v"), (None, ""), (9, None)]
    assert sorted(map(str, map(tuple, kept))) == sorted(map(str, want))
