"""Quotation linking against brute force on conversations with quotes."""

import random

from telemetry_insight.llm import chat_quotes

ROW = "conv_id long, turn long, role string, text string"


def test_part_of_a_message_is_linked(spark):
    rows = [(1, 0, "user", "one\ntwo\nthree\nfour"), (1, 1, "user", "other\nwords"), (1, 2, "user", "> Two\n> three\nyes"), (1, 3, "user", "> two\n> four\nno"), (1, 4, "user", "> two\n>\n> three\n> four\n!")]
    got = {r["turn"]: (r["reply_to"], r["linked"]) for r in chat_quotes.link_replies(spark.createDataFrame(rows, ROW)).collect()}
    assert got == {0: (None, False), 1: (0, False), 2: (0, True), 3: (2, False), 4: (0, True)}


def test_quoted_conversations(spark):
    r = random.Random(5)
    rows, want = [], {}
    for conv in range(12):
        said, parent = {}, {}
        for turn in range(r.randint(1, 9)):
            said[turn] = [f"c{conv} t{turn} l{i}" for i in range(r.randint(1, 5))]
            quote, parent[turn] = [], turn - 1 if turn else None
            if turn and r.random() < 0.6:
                to = r.randrange(turn)
                i = r.randrange(len(said[to]))
                quote, parent[turn] = said[to][i : r.randint(i + 1, len(said[to]))], to
            rows.append((conv, turn, "user", "\n".join(["> " + x for x in quote] + said[turn])))

        def walk(t):
            return [t] + [y for c in sorted(c for c in parent if parent[c] == t) for y in walk(c)]

        want[conv] = [(t, parent[t], "\n".join(said[t])) for t in walk(0)]
    r.shuffle(rows)
    got = {x["conv_id"]: [(m["turn"], m["reply_to"], m["text"]) for m in x["messages"]] for x in chat_quotes.conversations(spark.createDataFrame(rows, ROW)).collect()}
    assert got == want
    assert any([t for t, *_ in m] != sorted(t for t, *_ in m) for m in want.values())
