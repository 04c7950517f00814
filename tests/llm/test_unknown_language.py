"""Documents without a known language are judged by words too."""

from __future__ import annotations

import random

from tracefl.llm import quality_rules


def test_made_up_words_without_a_language(spark):
    rng = random.Random(2)
    common = ["the", "of", "and", "to", "in", "is", "that", "it"]
    made = lambda: "".join(rng.choice("etaoinshrdlu") for _ in range(rng.randint(3, 8)))
    text = lambda share: " ".join(rng.choice(common) if rng.random() < share else made() for _ in range(300))
    rows = [(i, text(0.4), "en") for i in range(20)] + [(100, text(0.4), None), (101, text(0.0), None), (102, text(0.0), "xx")]
    got = {r["doc_id"]: r for r in quality_rules.judge(spark.createDataFrame(rows, "doc_id long, text string, lang string"), most_chars=1.0).collect()}
    assert got[101]["js_words"] > 0.42 > got[100]["js_words"] > 0
    assert not got[101]["kept"] and not got[102]["kept"]
