"""Leaks whose names start sentences, and items without a usable template window."""

from tricount.llm import decontam

ITEM = "Tom has 12 marbles. Anna has 7 more than Tom. Paul has twice as many as Anna. How many marbles does Paul have?"


def found(spark, texts, item):
    d = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    return {r.doc_id for r in decontam.leaks(d, spark.createDataFrame([(1, item)], "item_id long, text string")).collect()}


def test_names_that_start_sentences(spark):
    changed = ITEM.replace("Tom", "Zoe").replace("Anna", "Rita").replace("Paul", "Igor").replace("12", "31")
    mixed = ITEM.replace("Tom has", "Zoe has").replace("than Tom", "than Rita").replace("Anna", "Rita").replace("Paul", "Igor")
    assert found(spark, ["So it was. " + changed + " Yes.", "So it was. " + ITEM, "nothing of it", mixed.replace("Igor have", "Rita have")], ITEM) == {0, 1}


def test_item_of_numbers(spark):
    item = "12 + 30 = 42 and 7 - 5 = 2"
    assert found(spark, [f"see: {item} so", "12 + 31 = 43 and 8 - 5 = 3", "no"], item) == {0}
