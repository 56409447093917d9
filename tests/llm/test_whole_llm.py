"""Training-data operators keep and drop the same rows whatever the size of a side input."""

from __future__ import annotations

from subcount.llm import decontam

SCHEMA = "doc_id long, text string, spans string"


def test_decontamination_in_chunks_judges_each_row_by_itself(spark):
    """Null ids, repeated ids with one clean and one contaminated row, and a hit share that two chunks make together."""
    dirty, clean = "ab cd", "some quite other words"
    both = " ".join(["ab cd", *["x"] * 38, "ef gh", *["x"] * 38])  # 4 of 80 words hit, 2 of 80 by one item alone
    rows = [(None, dirty, "a"), (None, clean, "b"), (1, dirty, "c"), (1, clean, "d"), (2, clean, "e"), (2, clean, "f"), (3, None, "g"), (4, "", "h"), (5, both, "i")]
    docs = spark.createDataFrame(rows, SCHEMA)
    items = spark.createDataFrame([(1, "ab cd"), (2, "ef gh"), (3, "never met")], "item_id long, text string")
    assert decontam.chunks_of(items, 1) > 1
    for n in (1, decontam.MAX_WORDS):
        got = decontam.drop_contaminated(docs, items, max_words=n)
        assert got.columns == docs.columns
        assert sorted(r["spans"] for r in got.collect()) == ["b", "d", "e", "f", "g", "h"]
    verdicts = [sorted(decontam.contamination(docs, items, max_words=n).collect(), key=str) for n in (1, decontam.MAX_WORDS)]
    assert verdicts[0] == verdicts[1]
