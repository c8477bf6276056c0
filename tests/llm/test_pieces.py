"""The encoder over moved, repeated, empty and odd input, and without the lists of units."""

import random

import pyarrow as pa
import pytest

from telemetry_insight.llm import piece_lattice

DOC = "doc_id long, text string, ids string, block long"


@pytest.fixture(scope="module")
def model():
    import sentencepiece

    return sentencepiece.SentencePieceProcessor(model_file=piece_lattice.MODEL), piece_lattice.Pieces.load()


def test_query_over_moved_and_repeated_rows(spark, model, tmp_path):
    sp, pieces = model
    r = random.Random(3)
    say = lambda n: " ".join("".join(r.choice("abcdeéß▁ \n字") for _ in range(r.randint(1, 9))) for _ in range(n))
    rows = [(i, say(r.randint(0, 60))) for i in range(200)] + [(5, "x"), (5, "x"), (None, "null id"), (7, None), (8, ""), (9, "z" * 70_000), (10, "a " * 30_000)]
    d = spark.createDataFrame([(i, t, "s", 1) for i, t in rows], DOC)
    moved = d.repartition(7).unionByName(d.limit(0))
    got = piece_lattice.encode(moved, pieces, back=True).collect()
    key = lambda x: (x[0] is None, x[0] or 0, x[1] or "", x[1] is None)
    assert sorted(((x["doc_id"], x["text"]) for x in got), key=key) == sorted(rows, key=key)
    for x in got:
        assert x["ids"] == (None if x["text"] is None else sp.encode(x["text"]))
        assert x["decoded"] == (None if x["text"] is None else x["text"].replace("▁", " "))
    d.select("doc_id", "text").write.parquet(f"file://{tmp_path}/documents.parquet")
    table = piece_lattice.op4_sentencepiece(spark, f"file://{tmp_path}")
    assert table.count() == table.where("same_text").count() == len(rows)


def test_empty_table(spark, model):
    assert piece_lattice.encode(spark.createDataFrame([], DOC), model[1], back=True).count() == 0


def test_a_block_without_its_list_is_encoded_all_the_same(model):
    sp, pieces = model
    table = pa.table({"doc_id": pa.array([1, 2]), "text": pa.array(["Some words, bytes ① and\n lines", None])})
    (pack,) = piece_lattice._pack(iter(table.to_batches()))
    left = pa.table({"block": pack.column(0), "docs": pack.column(1)})
    none = pa.table({"block": pa.array([], pa.int64()), "place": pa.array([], pa.int32()), "bounds": pa.array([], pa.int64())})
    got = piece_lattice._encode_block(pieces, True)(left, none).to_pylist()
    assert [x["ids"] for x in got] == [sp.encode("Some words, bytes ① and\n lines"), None]
    assert piece_lattice._encode_block(pieces, True)(left.slice(0, 0), none).num_rows == 0


def test_python_viterbi_equals_the_fold(spark, model):
    pieces = piece_lattice.Pieces(model[1].texts, [-(1 + i % 97) for i in range(len(model[1].texts))], model[1].usable, model[1].byte_ids, model[1].unknown, "unigram")
    units = ["▁hello", "tokenization", "▁unbelievable", "①x", "\n"]
    total = lambda ids: sum(pieces.scores[i] for i in ids)
    for x in piece_lattice.encode_units(spark.createDataFrame([(u,) for u in units], "unit string"), pieces).collect():
        assert total(x["ids"]) == total(pieces.path(x["unit"])), x["unit"]
