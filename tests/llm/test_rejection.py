"""Texts of a language that was not learned are rejected."""

import random

from pyspark.sql import functions as F

from tricount.llm import langid


def test_unlearned_language_is_rejected(spark):
    rng = random.Random(4)
    words = {"en": "the river runs down to old stone bridge where people walk and talk about weather news".split(), "de": "der fluss fliesst zur alten bruecke wo leute gehen und ueber das wetter sprechen".split(), "fi": "joki virtaa vanhalle kivisillalle jossa ihmiset kulkevat ja puhuvat saasta uutisista".split()}
    rows = [(i, " ".join(rng.choice(words[x]) for _ in range(40)), x) for i, x in enumerate(["en", "de", "fi"] * 60)]
    d = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = {r.doc_id: r for r in langid.identify(d, langid.train(d, F.col("lang") != "fi")).collect()}
    assert all(got[i].rejected for i, _, x in rows if x == "fi")
    own = [got[i].rejected for i, _, x in rows if x != "fi"]
    assert 0 < sum(own) <= 6  # about ``strict`` of each centroid's sample
