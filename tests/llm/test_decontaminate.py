"""Blocks of a large benchmark give the rows of one index."""

import random

from telemetry_insight.llm import decontaminate


def test_blocks_change_nothing(spark, monkeypatch):
    r = random.Random(9)
    say = lambda n: " ".join(f"w{int(r.random() ** 3 * 300)}" for _ in range(n))
    items = [(i, f"{say(r.randint(3, 30))}? {say(r.randint(1, 12))}") for i in range(40)] + [(40, "w1"), (41, None), (42, "..")]
    texts = [t.split() for _, t in items if t]
    part = lambda t: " ".join(t[: max(1, int(len(t) * r.uniform(0.4, 1)))])
    docs = spark.createDataFrame([(d, " ".join([say(50), part(r.choice(texts)), say(r.randint(0, 60)), " ".join(r.choice(texts)), say(9)])) for d in range(60)], "doc_id long, text string")
    bench = spark.createDataFrame(items, "item_id long, text string")
    rows = lambda: sorted(tuple(round(x, 9) for x in row) for row in decontaminate.leaks(docs, bench, overlap=0.3).collect())
    one = rows()
    monkeypatch.setattr(decontaminate, "INDEX_ITEMS", 9)
    assert len(one) > 20 and rows() == one
