"""Cases that a plain table does not hold: clashing columns, null and repeated ids, huge numbers, real legacy archives, the whole pipeline."""

import collections
import gzip
import random
import time

import numpy as np
import pytest

from telemetry_insight.llm import archives, decontaminate, line_dedup, topk, toxicity

LONG = "A line that is long enough to count"


def test_line_dedup_replaces_clashing_columns_and_sorts_its_stream(spark):
    rows = [(i, f"{LONG}\n{i}", 7, "k", "i", "r") for i in range(4)] + [(None, f"{LONG}\n{LONG}", 7, "k", "i", "r"), (9, None, 7, "k", "i", "r")]
    d = spark.createDataFrame(rows, "doc_id long, text string, n_lines int, kept_text string, _id string, _ROW string")
    got = line_dedup.apply_bitmaps(d, line_dedup.line_bitmaps(d)).collect()
    assert {(x["doc_id"], x["n_lines"], x["n_dropped"], x["kept_text"], x["_id"], x["_ROW"]) for x in got} == {
        (0, 2, 1, "0", "i", "r"), (1, 2, 1, "1", "i", "r"), (2, 2, 1, "2", "i", "r"), (3, 2, 0, f"{LONG}\n3", "i", "r"), (None, 2, 2, "", "i", "r"), (9, 1, 0, "", "i", "r"),
    }
    import inspect

    assert "sortWithinPartitions" in inspect.getsource(line_dedup.line_bitmaps)
    hits = spark.createDataFrame([(1, 2, 3, 4)], "row_key long, doc_id long, hash long, pos int")
    ranged = hits.repartitionByRange(3, "hash", "doc_id").sortWithinPartitions("hash", "doc_id", "pos")
    from pyspark.sql import functions as F

    plan = ranged.groupBy("hash", "doc_id").agg(F.collect_list(F.struct("row_key", "pos")))._jdf.queryExecution().executedPlan().toString()
    assert "Sort [hash" in plan and plan.count("Exchange") == 1  # the order is kept, and grouping needs no other exchange


def test_toxicity_with_clashing_columns_and_repeated_ids(spark):
    r = random.Random(4)
    say = lambda n, bad: " ".join([f"w{r.randrange(200)}" for _ in range(n)] + ["vile", "rotten"] * (2 * bad))
    rows = [(i, say(30, i % 3 == 0), 5.0, 9) for i in range(150)] + [(3, say(30, 0), 5.0, 9), (None, "vile", 5.0, 9)]
    d = spark.createDataFrame(rows, "doc_id long, text string, score double, PREDICTED int")
    labels = spark.createDataFrame([(i, int(i % 3 == 0)) for i in range(150)] + [(i, 1) for i in range(10_000, 10_050)], "doc_id long, toxic int")
    once = {(x["doc_id"], x["text"]): x["score"] for x in toxicity.score(d, labels).collect()}
    again = {(x["doc_id"], x["text"]): x["score"] for x in toxicity.score(d.repartition(5), labels).collect()}
    assert once == pytest.approx(again) and all(0 <= x <= 1 for x in once.values())
    assert toxicity.score(d, labels).columns == ["doc_id", "text", "score", "predicted"]


def test_leaks_of_null_and_repeated_ids(spark):
    item, other = "What is the capital of the northern province of old? It is the town of Everly.", "Who carried the seven lamps over the frozen lake at night? The miller of Tarn did."
    d = spark.createDataFrame([(1, f"so {item} indeed"), (1, f"so {other} indeed"), (None, item), (2, "nothing of it")], "doc_id long, text string")
    b = spark.createDataFrame([(None, item), (7, other), (7, item), (8, other)], "item_id long, text string")
    got = {(x["doc_id"], x["item_id"]) for x in decontaminate.leaks(d, b).collect()}
    assert got == {(1, None), (1, 7), (1, 8), (None, None), (None, 7)}


def test_products_are_exact():
    x = np.array([[2.0**40 + 1, 1], [2.0**40, 3]])
    row = np.array([2.0**20, 2.0**20 + 1])
    assert topk._products(x, row).tolist() == [int(2**40 + 1) * 2**20 + 2**20 + 1, 2**60 + 3 * (2**20 + 1)]
    assert topk._products(np.array([[1e30], [-1e30], [3.0]]), np.array([1e30])).tolist() == [(1 << 63) - 1, -(1 << 63), (1 << 63) - 1]


def test_topk_of_large_components_and_repeated_queries(spark):
    big = 2.0**24
    rows = [(0, [big, 1.0]), (0, [1.0, 1.0]), (1, [big, 3.0]), (2, [big, 2.0]), (3, [1e38, 1.0]), (4, [-1e300, 0.0]), (5, [0.25])]
    v = topk.scaled(spark.createDataFrame(rows, "vec_id long, embedding array<double>"))
    got = topk.nearest(v, v.where("vec_id = 1"), 3, pivots=4).orderBy("rank").collect()
    score = lambda a, b: sum(int(64 * x) * int(64 * y) for x, y in zip(a, b))
    assert [(x["vec_id"], x["score"]) for x in got] == [(3, (1 << 63) - 1), (2, score(rows[2][1], rows[3][1])), (0, score(rows[2][1], rows[0][1]))]
    assert topk.nearest(v.limit(0), v, 3).count() == 0


def test_members_take_time_in_proportion():
    member = gzip.compress(np.random.default_rng(0).bytes(1500))
    began = time.time()
    assert sum(1 for _ in archives.members(member * 4000)) == 4000
    assert time.time() - began < 20
    with pytest.raises(ValueError):
        list(archives.members(member * 2 + member[:-9]))


def test_a_folder_of_legacy_archives(spark, tmp_path):
    """Both versions, plain and zipped, without any header of ours, and records that are not HTTP."""
    web = b"HTTP/1.0 200 OK\nServer: x\r\n\r\n<p>one</p>"
    for version, name in ((1, "a.arc"), (2, "b.arc.gz")):
        block = f"{version} 0 org\n{archives.ARC_FIELDS[version]}\n".encode()
        parts = [archives.arc_line("filedesc://x", "0.0.0.0", "20010203040506", "text/plain", len(block), version) + block + b"\n"]
        for url, kind, body in (("http://h/p", "text/html", web), ("dns:h", "text/dns", b"20010203040506\nh. 60 IN A 1.2.3.4\n"), ("http://h/empty", "text/html", b"")):
            parts.append(archives.arc_line(url, "1.2.3.4", "20010203040506", kind, len(body), version) + body + b"\n")
        (tmp_path / name).write_bytes(b"".join(map(gzip.compress, parts)) if name.endswith("gz") else b"".join(parts))
    got = sorted(((x["url"], x["at"], x["archive_date"], x["result_code"], bytes(x["body"])) for x in archives.read_arc(spark, f"file://{tmp_path}").collect()), key=lambda x: (x[0], x[3] or ""))
    assert [x[0] for x in got] == ["dns:h", "dns:h", "http://h/empty", "http://h/empty", "http://h/p", "http://h/p"] and {x[3] for x in got} == {None, "200"}
    archives.convert_arc(spark, f"file://{tmp_path}", f"file://{tmp_path}/out")
    archives.convert_arc(spark, f"file://{tmp_path}", f"file://{tmp_path}/out")  # a repeated run leaves the same files
    made = collections.Counter((x["url"], x["record_type"], x["warc_date"], x["payload_digest"]) for x in archives.read_warc(spark, f"file://{tmp_path}/out").collect())
    assert set(made.values()) == {2} and {(u, t) for u, t, _, _ in made} == {("http://h/p", "response"), ("dns:h", "resource"), ("http://h/empty", "resource")}
    assert {d for _, _, d, _ in made} == {"2001-02-03T04:05:06Z"} and archives.sha1_base32(b"<p>one</p>") in {x[3] for x in made}


def test_pipeline_end_to_end_with_clashing_columns(spark, tmp_path):
    corpus_pipeline = pytest.importorskip("corpus_pipeline")
    import sentencepiece

    from telemetry_insight.llm import piece_lattice

    r = random.Random(6)
    say = lambda n: " ".join(f"w{r.randrange(5000)}" for _ in range(n))
    base, item = say(60), "What is the capital of the northern province of old? It is the town of Everly."
    rows = [(i, say(40) + f"\n{LONG}") for i in range(6)]
    rows += [(10 + i, base + f" tail{i}") for i in range(3)] + [(20, f"{say(20)} {item}"), (21, None), (22, ""), (None, "no id here")]
    bad = [(100 + i, say(25) + (" vile rotten" * 2 if i % 2 else "")) for i in range(60)]
    kind = "doc_id long, text string, n_chars long, score string, n_lines string, component_id string, rest int"
    spark.createDataFrame([(i, t, len(t or ""), "s", "l", "c", 1) for i, t in rows + bad], kind).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, 1, int("vile" in t)) for i, t in bad], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    got = {x["doc_id"]: x["ids"] for x in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    clean = [(i, t) for i, t in rows + bad if "vile" not in (t or "")]
    want = {i: t for i, t in clean if i not in (11, 12, 20)}
    want |= {i: t.removesuffix(f"\n{LONG}") for i, t in rows[:5]}  # the largest doc_id keeps the line
    sp = sentencepiece.SentencePieceProcessor(model_file=piece_lattice.MODEL)
    assert got == {i: None if t is None else sp.encode(t) for i, t in want.items()}
