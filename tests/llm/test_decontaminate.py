"""Partial copies whose placeholders are not consistent throughout."""

from __future__ import annotations

from logsketch.llm import decontaminate


def test_altered_slot_leaves_the_longest_consistent_run(spark):
    item = "the old mill by the river ground 3 sacks of corn every morning and the miller sold all of them at the market for silver while his daughter counted 3 coins into a wooden box"
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    for text, many in ((item, 35), (item.replace("counted 3", "counted 4"), 29), (item.replace("3 sacks", "5 sacks"), 29)):
        got = decontaminate.leaks(spark.createDataFrame([(1, "preface words here. " + text)], "doc_id long, text string"), bench).collect()
        assert [r.item_id for r in got] == [1] and got[0].shared_words == many, (got, many)
