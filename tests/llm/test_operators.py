"""Training-data operators against brute force on small fixtures: nulls, empties, ties, repeats, clashing columns, empty tables."""

import base64
import collections
import hashlib
import random
import re

import numpy as np
import pyarrow as pa
import pytest

from telemetry_insight.llm import archives, chat_quotes, components, decontaminate, jaccard_join, line_dedup, piece_lattice, sharding, substring_dedup, topk, toxicity, wordhash

GAP = re.compile(r"[\x20\x09-\x0D]+")
DOC = "doc_id long, text string, hash string, n long"


def words(text):
    return [w for w in GAP.split(text or "") if w]


def docs(spark, rows):
    """Documents with columns whose names operators use inside."""
    return spark.createDataFrame([(i, t, "x", 0) for i, t in rows], DOC)


@pytest.fixture(scope="module")
def corpus():
    r = random.Random(7)
    vocabulary = ["".join(r.choice("abcdeé") for _ in range(r.randint(2, 6))) for _ in range(120)]
    say = lambda n: " ".join(r.choice(vocabulary) for _ in range(n))
    shared, base = say(60), say(80)
    rows = [(i, say(r.randint(0, 90))) for i in range(30)]
    rows += [(i, say(20) + "\n" + shared + "\n" + say(10)) for i in range(30, 40)]
    for i in range(40, 60):  # near copies
        w = base.split()
        for _ in range(r.randint(0, 3)):
            w[r.randrange(len(w))] = r.choice(vocabulary)
        rows.append((i, " ".join(w)))
    rows += [(60, None), (61, ""), (62, "one"), (63, "One"), (64, "a b c"), (65, base), (66, base), (67, "\n\n"), (68, "x" * 5000)]
    return rows


def test_words_and_windows():
    texts = ["a b  c", None, "", "\tÉa b\n", "a b c d"]
    h, ends = wordhash.word_hashes(pa.array(texts))
    assert np.diff(ends).tolist() == [len(words(t)) for t in texts]
    assert h[0] == h[ends[4]] and h[0] != h[1]
    w, at, ptr = wordhash.windows(h, ends, 3)
    assert np.diff(ptr).tolist() == [1, 0, 0, 0, 2] and w[0] == w[1]


def test_line_dedup(spark, corpus):
    long = "A line that is long enough to count"
    rows = [*corpus, (70, f"{long}\nx"), (71, f"  {long.lower()}\t\n{long}"), (72, f"{long}\n{long}\nend"), (73, "short\nshort"), (74, "short"), (75, "short")]
    keys = lambda t: [x.strip(" \t\n\v\f\r").translate({i: i + 32 for i in range(65, 91)}) for x in (t or "").split("\n")]
    held = collections.defaultdict(set)
    for i, t in rows:
        for k in keys(t):
            if len(k) >= 20:
                held[k].add(i)
    want = {}
    for i, t in rows:
        kept = [x for x, k in zip((t or "").split("\n"), keys(t), strict=True) if not (len(held[k]) >= 3 and i != max(held[k]))]
        want[i] = (len(keys(t)), len(keys(t)) - len(kept), "\n".join(kept))
    d = docs(spark, rows)
    got = line_dedup.apply_bitmaps(d, line_dedup.line_bitmaps(d))
    assert {r["doc_id"]: (r["n_lines"], r["n_dropped"], r["kept_text"]) for r in got.collect()} == want
    assert line_dedup.apply_bitmaps(docs(spark, []), line_dedup.line_bitmaps(docs(spark, []))).count() == 0


def test_substring_dedup(spark, corpus):
    seen, want = set(), {}
    for i, t in sorted(corpus, key=lambda x: x[0]):
        w, gone = words(t), set()
        for at in range(len(w) - 19):
            k = tuple(w[at : at + 20])
            if k in seen:
                gone |= set(range(at, at + 20))
            seen.add(k)
        want[i] = (len(w), len(gone), " ".join(x for at, x in enumerate(w) if at not in gone))
    got = substring_dedup.remove_repeated_windows(docs(spark, corpus)).collect()
    assert {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_text"]) for r in got} == want
    assert sum(b - a for r in got for a, b in r["removed"]) == sum(x[1] for x in want.values())
    assert substring_dedup.remove_repeated_windows(docs(spark, [])).count() == 0


def linked(rows):
    """doc_id -> smallest doc_id reachable; rows: (doc_id, text)."""
    sets = []
    for i, t in rows:
        w = words((t or "").translate({i: i + 32 for i in range(65, 91)}))
        sets.append((i, {tuple(w[a : a + 5]) for a in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()))
    root = {i: i for i, _ in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for k, (a, x) in enumerate(sets):
        for b, y in sets[k + 1 :]:
            if x and y and 100 * len(x & y) >= 80 * len(x | y):
                lo, hi = sorted((find(a), find(b)))
                root[hi] = lo
    return sets, {i: find(i) for i, _ in sets}


def test_jaccard_join(spark, corpus):
    sets, root = linked(corpus)
    got = jaccard_join.near_components(docs(spark, corpus)).collect()
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got} == {i: (len(s), root[i]) for i, s in sets}
    assert jaccard_join.near_components(docs(spark, [])).count() == 0


def test_jaccard_join_of_repeated_ids_and_null_ids(spark, corpus):
    a, b = corpus[0][1] or "", " ".join(f"q{i}" for i in range(30))
    a = a if len(a) > 60 else " ".join(f"p{i}" for i in range(30))
    rows = [(1, a), (5, a), (5, b), (9, b), (7, "other words than those"), (None, a)]
    got = jaccard_join.near_components(docs(spark, rows)).collect()
    assert sorted((r["doc_id"], r["component_id"]) for r in got if r["doc_id"] is not None) == [(1, 1), (5, 1), (5, 1), (7, 7), (9, 1)]
    assert [(r["n_shingles"] > 0, r["component_id"]) for r in got if r["doc_id"] is None] == [(True, None)]


def test_jaccard_join_of_a_large_group_over_small_blocks(spark, monkeypatch):
    r = random.Random(11)
    base = [f"w{i}" for i in range(120)]
    rows = []
    for i in range(160):  # half near copies, half texts that share much and link with few
        w = list(base)
        for _ in range(r.choice([1, 1, 2, 9])):
            w[r.randrange(len(w))] = f"x{r.randrange(1000)}"
        rows.append((i, " ".join(w)))
    rows += [(500 + i, " ".join(f"l{k}" for k in range(3000)) + f" end{i}") for i in range(3)]
    for name, value in (("LIST_BLOCK", 40), ("HEADS", 2)):
        monkeypatch.setattr(jaccard_join, name, value)
    got = jaccard_join.near_components(docs(spark, rows)).collect()
    assert {x["doc_id"]: x["component_id"] for x in got} == linked(rows)[1]


def test_jaccard_join_candidates_do_not_grow_with_the_square_of_a_group(spark, monkeypatch):
    """Texts of one base, most of them too far apart to link: candidate rows stay within a few times the texts, also in many blocks of a room."""
    r, rows, stored, counts = random.Random(5), [], jaccard_join.common.stored, {}
    for i in range(240):
        w = [f"w{k}" for k in range(140)]
        for at in r.sample(range(140), 2):
            w[at] = f"x{r.randrange(100000)}"
        rows.append((i, " ".join(w)))

    def counted(session, df, name):
        out = stored(session, df, name)
        if name in ("near", "pairs"):
            counts[name] = counts.get(name, 0) + out.count()
        return out

    monkeypatch.setattr(jaccard_join.common, "stored", counted)
    monkeypatch.setattr(jaccard_join, "ROOM_ELEMENTS", 5000, raising=False)
    got = jaccard_join.near_components(docs(spark, rows)).collect()
    assert {x["doc_id"]: x["component_id"] for x in got} == linked(rows)[1]
    assert counts["near"] + counts["pairs"] <= 10 * len(rows), counts


def test_jaccard_forest_connects_the_same():
    pairs = np.random.default_rng(1).integers(0, 60, (90, 2)) * 7 - 100
    kept = jaccard_join.forest(pairs)

    def roots(edges):
        root = {int(x): int(x) for x in pairs.ravel()}
        for _ in root:
            for a, b in edges.tolist():
                root[a] = root[b] = min(root[a], root[b])
        return root

    assert roots(kept) == roots(pairs)
    assert len(kept) == len(roots(pairs)) - len(set(roots(pairs).values()))
    assert len(jaccard_join.forest(pairs[:0])) == 0


def test_jaccard_boundary_follows_costs():
    sizes = {10: 100, 50: 100, 150: 10}
    assert jaccard_join.choose_boundary(sizes, 0.0, 80) <= jaccard_join.choose_boundary(sizes, 50.0, 80)


def test_parity_maps_bound_the_difference():
    r = np.random.default_rng(3)
    a = np.unique(r.integers(0, 1 << 63, 500).astype(np.uint64))
    b = np.unique(np.concatenate([a[:450], r.integers(0, 1 << 63, 300).astype(np.uint64)]))
    x, y = jaccard_join.parity_map(a), jaccard_join.parity_map(b)
    u, v = jaccard_join._map_bits([x, y], min(len(x), len(y)))
    assert np.bitwise_count(u ^ v).sum() <= len(set(a.tolist()) ^ set(b.tolist()))


def test_components(spark):
    edges = [(1, 2), (2, 3), (10, 9), (9, 8), (8, 7), (5, 5)]
    got = components.components(spark.createDataFrame(edges, "a long, b long"))
    assert {r["node"]: r["component"] for r in got.collect()} == {1: 1, 2: 1, 3: 1, 7: 7, 8: 7, 9: 7, 10: 7}


def test_toxicity_learns_and_scores_all(spark):
    r = random.Random(1)
    say = lambda n: [f"w{r.randrange(300)}" for _ in range(n)]
    rows, labels = [], []
    for i in range(400):
        w, bad = say(r.randint(20, 80)), i % 4 == 0
        if bad:
            for _ in range(4):
                w.insert(r.randrange(len(w)), r.choice(["vile", "rotten"]))
        rows.append((i, " ".join(w)))
        labels.append((i, 0, int(bad)))
    rows += [(1000, None), (1001, "")]
    got = toxicity.score(docs(spark, rows), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")).collect()
    by = {x["doc_id"]: x for x in got}
    assert len(by) == 402 and all(0 <= x["score"] <= 1 and x["predicted"] == int(x["score"] >= 0.5) for x in got)
    assert sum(by[i]["predicted"] == t for i, _, t in labels) >= 390 and by[1000]["predicted"] == 0
    one = toxicity.score(docs(spark, rows[:3]), spark.createDataFrame([], "doc_id long, quality int, toxic int"))
    assert {x["score"] for x in one.collect()} == {0.0}


def test_block_max_wand_finds_what_a_full_scan_finds():
    r = random.Random(5)
    vocabulary = [f"t{i}" for i in range(400)]
    items = [(i, " ".join(r.choice(vocabulary) for _ in range(r.randint(5, 30))) + ". Answer " + r.choice(vocabulary)) for i in range(300)]
    index = decontaminate.Index(items, 0.3)
    for _ in range(40):
        base = items[r.randrange(300)][1].split() + [r.choice(vocabulary) for _ in range(20)]
        terms = set(wordhash.word_hashes(pa.array([" ".join(base)]), lower=True, punctuation=True)[0].tolist())
        full = collections.Counter()
        for t in terms & set(index.posts):
            for i, x in zip(*index.posts[t], strict=True):
                full[int(i)] += x
        assert sorted(i for i, _ in index.search(terms)) == sorted(i for i, x in full.items() if x >= 0.3 - 1e-9)


def test_decontamination(spark):
    item = "What is the capital of the northern province of old? It is the town of Everly by the sea."
    r = random.Random(2)
    filler = " ".join(f"w{r.randrange(900)}" for _ in range(400))
    rows = [(1, filler), (2, f"{filler} {item.upper()} {filler}"), (3, item), (4, "What is the capital of the northern province of old?"), (5, None), (6, "")]
    got = decontaminate.leaks(docs(spark, rows), spark.createDataFrame([(7, item), (8, None), (9, "")], "item_id long, text string"))
    assert sorted((x["doc_id"], x["item_id"]) for x in got.collect()) == [(2, 7), (3, 7)]
    assert decontaminate.leaks(docs(spark, rows), spark.createDataFrame([], "item_id long, text string")).count() == 0


MODEL = piece_lattice.MODEL


def test_bpe_encoding_equals_the_library(spark, data):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=MODEL)
    pieces = piece_lattice.Pieces.load(MODEL)
    rows = [(1, "a  b "), (2, " x\ny  "), (3, ""), (4, None), (5, "▁q ▁▁ z"), (6, "x" * 300 + " é①"), (7, " " * 40 + "a"), (8, "tab\there \n\n end"), (9, "word"), (9, "word two")]
    rows += [(r["doc_id"] + 100, r["text"]) for r in spark.read.parquet(f"{data}/documents.parquet").limit(60).collect()]
    coded = piece_lattice.decode(piece_lattice.encode(docs(spark, rows), pieces), pieces).collect()
    assert len(coded) == len(rows)
    for x in coded:
        assert x["ids"] == (None if x["text"] is None else sp.encode(x["text"]))
        assert x["decoded"] == (None if x["text"] is None else x["text"].replace("▁", " "))


def test_viterbi_equals_the_library(spark, tmp_path):
    import sentencepiece
    from sentencepiece import sentencepiece_model_pb2 as pb

    m = pb.ModelProto()
    m.ParseFromString(open(MODEL, "rb").read())
    m.trainer_spec.model_type = 1
    for i, p in enumerate(m.pieces):
        p.score = -float(np.log(i + 2)) - 0.001 * (i % 97)
    (tmp_path / "u.model").write_bytes(m.SerializeToString())
    sp = sentencepiece.SentencePieceProcessor(model_file=str(tmp_path / "u.model"))
    pieces = piece_lattice.Pieces.load(str(tmp_path / "u.model"), kind="unigram")
    units = ["▁hello", "▁worlds", "▁tokenization", "▁unbelievable", "▁Strasse", "▁a"]
    got = piece_lattice.encode_units(spark.createDataFrame([(u,) for u in units], "unit string"), pieces).collect()
    score = lambda ids: sum(pieces.scores[i] for i in ids)
    for r in got:
        assert score(r["ids"]) == pytest.approx(score(sp.encode(r["unit"][1:])), abs=1e-4)


def test_sharding(spark, corpus):
    d = docs(spark, corpus)
    records = sharding.with_slots(d, 64).selectExpr("doc_id", "size", "crc32(coalesce(text, '')) text_crc32", "virtual_slot")
    one = sharding.plan_map(sharding.slot_loads(records, 64), 8)
    rows = sharding.place(records, one).collect()
    load = collections.Counter()
    for r in rows:
        load[r["shard"]] += r["size"]
    assert {r["doc_id"]: r["size"] for r in rows} == {i: len((t or "").encode()) + 1 for i, t in corpus}
    for s in load:
        assert sorted(r["slot"] for r in rows if r["shard"] == s) == list(range(sum(r["shard"] == s for r in rows)))
    before = {r["virtual_slot"]: r["shard"] for r in one.collect()}
    for r in sharding.grow_map(one, 8).collect():
        assert r["version"] == 2 and r["shard"] in (before[r["virtual_slot"]], 8)


def test_arc_versions_convert_and_round_trip():
    for version in (1, 2):
        legacy = archives.arc_archive([("http://a b/é", "<p>é</p>".encode()), (None, b"")], version)
        records = list(archives.parse_arc(legacy))
        assert [r["URL"] for r in records] == ["http://a%20b/%C3%A9", "urn:empty"]
        (headers, body), = archives.parse_warc(archives.convert_record(records[0]))
        assert headers["WARC-Date"] == "2024-01-01T00:00:00Z" and body.endswith("<p>é</p>".encode())
        (again, _), = archives.parse_warc(archives.convert_record(records[1], 6, refers_to=-3))
        assert again["WARC-Type"] == "revisit" and archives.page_of(again["WARC-Refers-To"]) == -3
    with pytest.raises(ValueError):
        list(archives.parse_arc(legacy[:-20]))


def test_warc_query_form(spark, tmp_path):
    rows = [(3, "u", "same"), (1, "u", "same"), (2, None, None), (4, "v", ""), (9, "w", "other")]
    path = f"file://{tmp_path}/w"
    archives.write_warc(archives.with_revisits(spark.createDataFrame(rows, "page_id long, url string, html string")), path)
    got = {r["page_id"]: (r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in archives.read_warc(spark, path).collect()}
    sha = lambda t: base64.b32encode(hashlib.sha1(t.encode()).digest()).decode()
    assert got == {1: (4, sha("same"), "response", None), 3: (4, sha("same"), "revisit", 1), 2: (0, sha(""), "response", None), 4: (0, sha(""), "revisit", 2), 9: (5, sha("other"), "response", None)}


def test_topk_equals_brute_force(spark):
    r = np.random.default_rng(0)
    rows = [(i, r.normal(size=8).astype(np.float32).tolist()) for i in range(300)]
    rows += [(300, [0.5] * 8), (301, [0.5] * 8), (302, None), (303, [float("nan")] * 8), (304, [None] * 8), (305, [1.0])]
    v = topk.scaled(spark.createDataFrame(rows, "vec_id long, embedding array<float>"))
    got = collections.defaultdict(list)
    for x in topk.nearest(v, v.where("vec_id % 20 = 0"), 20, pivots=12).orderBy("query_id", "rank").collect():
        got[x["query_id"]].append((x["vec_id"], x["score"]))
    ok = {i: np.floor(64 * np.pad(np.array(x, np.float64), (0, 8 - len(x)))).astype(int) for i, x in rows if x and all(y is not None and y == y for y in x)}
    for q in (i for i in ok if i % 20 == 0):
        assert got[q] == sorted(((i, int(ok[q] @ y)) for i, y in ok.items() if i != q), key=lambda p: (-p[1], p[0]))[:20]


def test_quotes_are_linked_and_cut(spark):
    rows = [
        (1, 0, "user", "The bus is late."), (1, 1, "assistant", "Which one?"), (1, 2, "user", "Another thing"),
        (1, 3, "assistant", "> The  BUS is late.\nSorry."), (1, 4, "user", ">> The bus is late.\n> Sorry.\nThanks"), (1, 5, "user", None),
        (2, 0, "user", "> never said\nhello"), (3, 0, "user", ""),
    ]
    got = {(r["conv_id"], r["turn"]): r for r in chat_quotes.link_replies(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    assert (got[1, 3]["reply_to"], got[1, 3]["own_text"], got[1, 3]["linked"]) == (0, "Sorry.", True)
    assert (got[1, 4]["reply_to"], got[1, 4]["own_text"]) == (3, "Thanks")
    assert (got[1, 2]["reply_to"], got[1, 2]["linked"]) == (1, False)
    assert (got[2, 0]["own_text"], got[2, 0]["linked"], got[2, 0]["reply_to"]) == ("hello", False, None)
    assert chat_quotes.conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).count() == 3
