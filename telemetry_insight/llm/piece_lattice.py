"""SentencePiece encoding and decoding over a relational lattice.

A model is read into a piece table (piece, id, score). Texts are cut into units
that no piece crosses: runs of the space mark with the characters up to the
next one, and line breaks, cut again wherever two neighbours stand in no piece. Distinct units are exploded into substrings no longer
than the longest piece and equi-joined to the piece table; the edges of a unit
are grouped and folded with Spark's aggregate() into the places where its tokens start:

* unigram models: Viterbi, the path of the largest summed score;
* BPE models: edges by score, leftmost first, each joining its two neighbours
  if exactly one boundary lies inside it. Viterbi over a BPE model's scores is
  not that model's encoding, so this fold takes its place there; its state
  is a 64-bit map of the boundaries left.

Units the fold's map can't hold (over FOLD_CHARS characters, or long runs of
spaces, whose pieces all have one score) are merged from a heap in Python.

Text is not shuffled row by row: each task packs its documents into compressed blocks and
lists a block's distinct units; encodings come back per block, which is named by
its content. A repeated task that meets its rows in another order makes blocks of other
names; their units have no listing then, and are encoded where the block is.
Work on words is done on whole Arrow buffers. Decoding maps
ids to pieces, byte pieces to UTF-8 and space marks to spaces.

Defined cases: a null text gives null ids, an empty one none; characters outside
the model become their UTF-8 bytes; a space mark in a text decodes to a space,
as in the library; rows of one doc_id are encoded each on its own.
"""

from __future__ import annotations

import heapq
import io
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common, wordhash

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
MARK = "▁"
FOLD_CHARS, FOLD_RUN = 60, 14
UNKNOWN_PENALTY = 10.0


@dataclass(frozen=True)
class Pieces:
    """A model's pieces; kind is "bpe" or "unigram". Its size is the model's, whatever the corpus."""

    texts: list[str]
    scores: list[float]
    usable: list[bool]
    byte_ids: list[int]
    unknown: int
    kind: str = "bpe"
    prefix: bool = True
    ids: dict[str, int] = field(init=False, repr=False, compare=False)

    def __post_init__(self):
        object.__setattr__(self, "ids", {t: i for i, (t, ok) in enumerate(zip(self.texts, self.usable, strict=True)) if ok})

    @classmethod
    def load(cls, path: str = MODEL, kind: str = "bpe") -> Pieces:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        every = range(sp.get_piece_size())
        usable = [not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i)) for i in every]
        byte_ids = [sp.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
        return cls([sp.id_to_piece(i) for i in every], [sp.get_score(i) for i in every], usable, [] if sp.unk_id() in byte_ids else byte_ids, sp.unk_id(), kind)

    @cached_property
    def longest(self) -> int:
        return max(map(len, self.ids))

    @cached_property
    def raw(self) -> list[bytes]:
        """What each id decodes to."""
        out = [t.replace(MARK, " ").encode() if ok else b"" for t, ok in zip(self.texts, self.usable, strict=True)]
        for b, i in enumerate(self.byte_ids):
            out[i] = bytes([b])
        return out

    def spelled(self, char: str) -> list[int]:
        return [self.byte_ids[b] for b in char.encode()] if self.byte_ids else [self.unknown]

    @cached_property
    def neighbours(self) -> tuple[np.ndarray, np.ndarray]:
        """A number for each character that stands beside another in some piece (0: none), and which numbers do; no piece crosses a place between two others."""
        pairs = {(a, b) for t in self.ids for a, b in zip(t.replace(MARK, " "), t.replace(MARK, " ")[1:])}
        chars = sorted({c for p in pairs for c in p})
        code = {c: i + 1 for i, c in enumerate(chars)}
        alphabet = np.zeros(max(map(ord, chars), default=0) + 2, np.int32)
        alphabet[[ord(c) for c in chars]] = np.arange(1, len(chars) + 1)
        joins = np.zeros((len(chars) + 1, len(chars) + 1), bool)
        for a, b in pairs:
            joins[code[a], code[b]] = True
        return alphabet, joins

    def table(self, spark: SparkSession) -> DataFrame:
        """Pieces in both spellings, with the space mark and with a space. code: the rank of the score, the best first, above length and id."""
        ranks = {s: r for r, s in enumerate(sorted({self.scores[i] for i in self.ids.values()}, reverse=True))}
        rows = [(x, i, float(self.scores[i]), ranks[self.scores[i]] << RANK | min(len(t), 63) << LEN | i) for t, i in self.ids.items() for x in {t, t.replace(MARK, " ")}]
        return spark.createDataFrame(rows, "piece string, id int, score double, code long")

    def merged(self, unit: str) -> list[int]:
        """BPE by a heap of neighbours, best score and leftmost first."""
        n = len(unit)
        left, right, end = list(range(-1, n - 1)), [*range(1, n), -1], list(range(1, n + 1))
        alive, heap = [True] * n, []

        def offer(i: int) -> None:
            j = right[i] if i >= 0 else -1
            if j >= 0 and (k := self.ids.get(unit[i : end[j]])) is not None:
                heapq.heappush(heap, (-self.scores[k], i, end[i], end[j]))

        for i in range(n - 1):
            offer(i)
        while heap:
            _, i, mid, to = heapq.heappop(heap)
            j = right[i] if alive[i] else -1
            if j < 0 or end[i] != mid or end[j] != to:
                continue
            end[i], right[i], alive[j] = to, right[j], False
            if right[i] >= 0:
                left[right[i]] = i
            offer(left[i])
            offer(i)
        out, i = [], 0
        while 0 <= i < n:
            k = self.ids.get(unit[i : end[i]])
            out += self.spelled(unit[i]) if k is None else [k]
            i = right[i]
        return out

    def best(self, unit: str) -> list[int]:
        """Unigram: the path of the largest summed score."""
        low = min(s for s, ok in zip(self.scores, self.usable, strict=True) if ok) - UNKNOWN_PENALTY
        score, came = [0.0] + [-np.inf] * len(unit), [(0, -1)] * (len(unit) + 1)
        for end in range(1, len(unit) + 1):
            for start in range(max(0, end - self.longest), end):
                k = self.ids.get(unit[start:end], -1)
                if k < 0 and end - start > 1:
                    continue
                here = score[start] + (self.scores[k] if k >= 0 else low)
                if here > score[end]:
                    score[end], came[end] = here, (start, k)
        out, at = [], len(unit)
        while at:
            start, k = came[at]
            out.append([k] if k >= 0 else self.spelled(unit[start:at]))
            at = start
        return [i for part in reversed(out) for i in part]

    def path(self, unit: str) -> list[int]:
        """A unit's ids, in Python."""
        return self.merged(unit) if self.kind == "bpe" else self.best(unit)


#: Bits of an edge in a long: the rank of its score, its start, its length, its id plus 1.
RANK, START, LEN = 33, 27, 21
_AT, _LONG, _ID = f"cast(shiftright(e, {START}) & 63 as int)", f"cast(shiftright(e, {LEN}) & 63 as int)", f"cast(e & {(1 << LEN) - 1} as int) - 1"


def _found(units: DataFrame, pieces: Pieces, least: int) -> DataFrame:
    """unit, n, start, len and the piece, if it is one, of every substring of at least so many characters."""
    table = pieces.table(units.sparkSession)  # as many rows as the model has pieces, at most twice
    sized = units if "n" in units.columns else units.withColumn("n", F.length("unit"))
    spots = sized.where(F.col("n") >= least).select("unit", "n", F.explode(F.sequence(F.lit(0), F.col("n") - least)).alias("start"))
    subs = spots.select("unit", "n", "start", F.explode(F.sequence(F.lit(least), F.greatest(F.lit(least), F.least(F.lit(pieces.longest), F.col("n") - F.col("start"))))).alias("len"))
    return subs.withColumn("piece", F.expr("substring(unit, start + 1, len)")).join(F.broadcast(table), "piece", "inner" if least > 1 else "left")


def lattice(units: DataFrame, pieces: Pieces) -> DataFrame:
    """unit, n, edges: array of struct<score, start, len, id> of every substring that is a piece, and of single characters that are none (id -1).

    units must hold each unit once. They are dealt out by unit, and the grouping needs no other exchange.
    """
    low = min(s for s, ok in zip(pieces.scores, pieces.usable, strict=True) if ok) - UNKNOWN_PENALTY
    edge = F.struct(F.coalesce("score", F.lit(low)).alias("score"), F.col("start"), F.col("len"), F.coalesce("id", F.lit(-1)).alias("id"))
    return _found(units, pieces, 1).where(F.col("id").isNotNull() | (F.col("len") == 1)).groupBy("unit", "n").agg(F.collect_list(edge).alias("edges"))


def ranked_lattice(units: DataFrame, pieces: Pieces, least: int = 2) -> DataFrame:
    """unit, n, edges as lattice(), each edge a long that sorts by score and start. With least 2, units without an edge that joins characters are left out."""
    edge = F.coalesce("code", F.shiftleft(F.lit(1).cast("long"), LEN)).bitwiseOR(F.shiftleft(F.col("start").cast("long"), START)) + F.when(F.col("id").isNotNull(), 1).otherwise(0)
    return _found(units, pieces, least).where(F.col("id").isNotNull() | (F.col("len") == 1)).groupBy("unit", "n").agg(F.sort_array(F.collect_list(edge)).alias("edges"))


def fold_merges(ranked: DataFrame) -> DataFrame:
    """unit, edges, bounds by BPE: bit i of bounds is set if a token starts at character i, or the unit ends there."""
    ready = ranked.withColumn("spans", F.expr(f"transform(edges, e -> struct(shiftleft(shiftleft(1L, {_LONG} + 1) - 1, {_AT}) as span, shiftleft(shiftleft(1L, {_LONG}) + 1, {_AT}) as tips))"))
    # An edge of one character has no boundary inside.
    return ready.select("unit", "edges", F.expr("aggregate(spans, shiftleft(1L, n + 1) - 1, (s, e) -> if(bit_count(s & e.span) = 3 and (s & e.tips) = e.tips, (s & ~e.span) | e.tips, s))").alias("bounds"))


def fold_viterbi(edges: DataFrame) -> DataFrame:
    """unit, bounds by the best summed score: edges by end; the state holds, for each place, the best score and the start of the edge it came by."""
    ready = edges.select("unit", "n", F.expr("array_sort(transform(edges, e -> struct(e.start + e.len as end, e.start as start, e.score as score)))").alias("edges"))
    best = ready.withColumn("best", F.expr("""
        aggregate(edges, transform(sequence(0, n), i -> struct(if(i = 0, 0D, -1e300D) as score, -1 as start)),
            (s, e) -> if(s[e.start].score + e.score > s[e.end].score,
                         transform(s, (x, i) -> if(i = e.end, struct(s[e.start].score + e.score as score, e.start as start), x)), s))"""))
    return best.select("unit", F.expr("""
        aggregate(sequence(1, n), struct(n as at, shiftleft(1L, n) as bounds),
            (s, i) -> if(s.at <= 0, s, struct(best[s.at].start as at, s.bounds | shiftleft(1L, best[s.at].start) as bounds))).bounds""").alias("bounds"))


def unit_bounds(units: DataFrame, pieces: Pieces) -> DataFrame:
    """unit, bounds: where a unit's tokens start. BPE units in which nothing joins are left out."""
    return fold_merges(ranked_lattice(units, pieces)).select("unit", "bounds") if pieces.kind == "bpe" else fold_viterbi(lattice(units, pieces))


def encode_units(units: DataFrame, pieces: Pieces) -> DataFrame:
    """unit, ids: the tokens between the bounds, looked up in the piece table; characters without a piece as their bytes."""
    once = units.select("unit", F.length("unit").alias("n"))
    full = once.join(unit_bounds(units, pieces), "unit", "left").withColumn("bounds", F.coalesce("bounds", F.expr("shiftleft(1L, n + 1) - 1")))
    starts = full.select("unit", F.posexplode(F.expr("filter(sequence(0, n), i -> (shiftright(bounds, i) & 1) = 1)")).alias("k", "at"), F.expr("filter(sequence(0, n), i -> (shiftright(bounds, i) & 1) = 1)").alias("every"))
    tokens = starts.where(F.col("k") < F.size("every") - 1).select("unit", "k", F.expr("substring(unit, at + 1, every[k + 1] - at)").alias("piece"))
    named = tokens.join(F.broadcast(pieces.table(units.sparkSession).select("piece", "id")), "piece", "left")
    own = F.when(F.col("id").isNotNull(), F.array("id")).otherwise(_bytes(F.col("piece"), pieces))
    return named.groupBy("unit").agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("k", own.alias("ids")))), lambda x: x["ids"])).alias("ids"))


def _bytes(char: Column, pieces: Pieces) -> Column:
    """ids of a character without a piece."""
    if not pieces.byte_ids:
        return F.array(F.lit(pieces.unknown))
    if pieces.byte_ids != list(range(pieces.byte_ids[0], pieces.byte_ids[0] + 256)):
        raise ValueError("byte pieces are expected in a row")
    code = F.hex(F.encode(char, "UTF-8"))
    return F.transform(F.sequence(F.lit(1), F.octet_length(char)), lambda k: F.conv(F.substring(code, 2 * k - 1, F.lit(2)), 16, 10).cast("int") + pieces.byte_ids[0])


BLOCK_BYTES = 8 << 20


def _blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    held, size = [], 0
    for batch in batches:
        held.append(batch)
        size += batch.nbytes
        if size >= BLOCK_BYTES:
            yield pa.Table.from_batches(held).combine_chunks()
            held, size = [], 0
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def _block_id(table: pa.Table) -> int:
    """From the ids and texts of a block: blocks of one name hold the same rows, whichever task cut them."""
    x = table["doc_id"].cast(pa.int64()).fill_null(-(1 << 63)).to_numpy().astype(np.int64).view(np.uint64)
    raw, offsets = wordhash.buffers(table["text"])
    up, _ = wordhash.powers(wordhash.WORD_BASE, len(x))
    mark = wordhash.mix(x + wordhash.mix(offsets[1:].astype(np.uint64))) * up[: len(x)]
    return int(wordhash.mix(mark.sum(dtype=np.uint64, keepdims=True) ^ np.uint64(zlib.crc32(raw)))[0].view(np.int64))


def _strings(raw: np.ndarray, starts: np.ndarray) -> pa.Array:
    """Neighbouring pieces of a buffer as strings; starts has the end as its last entry. Nothing is copied."""
    return pa.Array.from_buffers(pa.large_string(), len(starts) - 1, [None, pa.py_buffer(np.ascontiguousarray(starts, np.int64)), pa.py_buffer(raw)])


@dataclass
class Units:
    """A block's texts as numbers: rows of units, units of parts that no piece crosses. Space marks are spaces here."""

    rows: np.ndarray  # row pointer into words
    words: pa.Array  # the unit of each word
    cuts: np.ndarray  # unit pointer into links
    links: pa.Array  # the part of each of a unit's places
    parts: pa.Array  # distinct parts

    @classmethod
    def of(cls, texts: pa.Array, pieces: Pieces) -> Units:
        texts = texts.combine_chunks() if isinstance(texts, pa.ChunkedArray) else texts
        texts = texts.cast(pa.large_string()).fill_null("")
        if pc.any(pc.match_substring(texts, MARK)).as_py():
            texts = pc.replace_substring(texts, MARK, " ")
        if pieces.prefix:
            texts = pc.if_else(pc.equal(pc.binary_length(texts), 0), texts, pc.binary_join_element_wise(pa.scalar(" ", pa.large_string()), texts, pa.scalar("", pa.large_string())))
        raw, offsets = wordhash.buffers(texts)
        line, space = raw == 10, raw == 32
        first = np.zeros(len(raw) + 1, bool)
        first[:-1] = line
        first[1:] |= line
        first[1:-1] |= space[1:] & ~space[:-1]
        first[offsets] = True  # rows, and the end
        starts = np.flatnonzero(first)
        del line, space, first
        rows = np.searchsorted(starts, offsets)
        coded = _strings(raw, starts).dictionary_encode()
        cuts, links, parts = cls._parts(coded.dictionary, pieces)
        return cls(rows, coded.indices, cuts, links, parts)

    @staticmethod
    def _parts(units: pa.Array, pieces: Pieces) -> tuple[np.ndarray, pa.Array, pa.Array]:
        raw, _ = wordhash.buffers(units)
        chars = np.frombuffer(raw.tobytes().decode().encode("utf-32-le"), np.uint32)
        begins = np.concatenate(([0], np.cumsum(pc.utf8_length(units).to_numpy()))).astype(np.int64)
        alphabet, joins = pieces.neighbours
        code = alphabet[np.minimum(chars, len(alphabet) - 1)]
        cut = np.ones(len(chars) + 1, bool)
        cut[1:-1] = ~joins[code[:-1], code[1:]]
        cut[begins] = True
        at = np.flatnonzero(cut)
        place = np.zeros(len(chars) + 1, np.int64)
        np.cumsum(1 + (chars >= 0x80) + (chars >= 0x800) + (chars >= 0x10000), out=place[1:])
        coded = _strings(raw, place[at]).dictionary_encode()
        return np.searchsorted(at, begins), coded.indices, coded.dictionary

    def listed(self) -> np.ndarray:
        """Places of the parts that the fold can hold; the others are few."""
        return np.flatnonzero(pc.and_(pc.less_equal(pc.utf8_length(self.parts), FOLD_CHARS), pc.invert(pc.match_substring(self.parts, " " * (FOLD_RUN + 1)))).to_numpy(zero_copy_only=False))


def _release() -> None:
    """A worker waits for its next task with as little memory as it can."""
    pa.default_memory_pool().release_unused()


def _list_units(pieces: Pieces):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _blocks(batches):
            block, units = _block_id(table), Units.of(table["text"], pieces)
            place = units.listed()
            for at in range(0, len(place), 50_000):
                part = place[at : at + 50_000]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), block, np.int64)), pa.array(part.astype(np.int32)), units.parts.take(pa.array(part)).cast(pa.string())], names=["block", "place", "unit"])
            del units, table
            _release()

    return run


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for table in _blocks(batches):
        out = io.BytesIO()
        with pa.ipc.new_stream(out, table.schema, options=pa.ipc.IpcWriteOptions(compression=pa.Codec("zstd", 6))) as f:
            f.write_table(table)
        yield pa.RecordBatch.from_arrays([pa.array([_block_id(table)], pa.int64()), pa.array([out.getvalue()], pa.binary())], names=["block", "docs"])
        del table, out
        _release()


def _encode_block(pieces: Pieces, back: bool):
    kind = np.dtype(np.uint16 if len(pieces.texts) < 1 << 16 else np.int32)
    names = pa.array([t.replace(MARK, " ") for t in pieces.ids], pa.large_string())
    numbers = np.array(list(pieces.ids.values()), kind)

    def spelled(parts: pa.Array, places: np.ndarray, bounds: np.ndarray) -> pa.Array:
        """The ids of each part, packed in bytes, from where its tokens start.

        Parts that were not listed, or whose listing was cut otherwise by a repeated task, are encoded here.
        """
        chars = pc.utf8_length(parts).to_numpy().astype(np.int64)
        first = np.concatenate(([0], np.cumsum(chars)))
        known = np.zeros(len(parts), bool)
        known[places] = True
        starts = np.ones(int(first[-1]), bool)
        owner = np.repeat(np.arange(len(parts)), chars)
        of = np.zeros(len(parts), np.int64)
        of[places] = bounds
        listed = np.flatnonzero(known[owner])
        starts[listed] = (of[owner[listed]] >> (listed - first[owner[listed]])) & 1
        raw, _ = wordhash.buffers(parts)
        lead = np.flatnonzero((raw & 0xC0) != 0x80)  # the byte that each character begins with
        at = np.flatnonzero(starts)
        tokens = _strings(raw, np.append(lead[at], len(raw)))
        found = pc.index_in(tokens, names).fill_null(-1).to_numpy()
        size = np.where(found >= 0, 1, 0)
        ids = numbers[np.maximum(found, 0)]
        odd = {}  # characters without a piece, and units beyond the fold
        for i in np.flatnonzero(found < 0).tolist():
            odd[i] = pieces.spelled(tokens[i].as_py())
            size[i] = len(odd[i])
        ends = np.concatenate(([0], np.cumsum(size)))
        flat = np.repeat(ids, size)
        for i, x in odd.items():
            flat[ends[i] : ends[i + 1]] = x
        cuts = ends[np.searchsorted(at, first)] * kind.itemsize
        out = pa.Array.from_buffers(pa.large_binary(), len(parts), [None, pa.py_buffer(cuts.astype(np.int64)), pa.py_buffer(flat)])
        missing = np.flatnonzero(~known)
        if not len(missing):
            return out
        row = np.arange(len(parts))
        row[missing] = len(parts) + np.arange(len(missing))
        own = [np.array(pieces.path(u.replace(" ", MARK)), kind).tobytes() for u in parts.take(pa.array(missing)).to_pylist()]
        return pa.concat_arrays([out, pa.array(own, pa.large_binary())]).take(pa.array(row))

    spelling = pa.array(pieces.raw, pa.large_binary()) if back else None
    schema = pa.schema([("doc_id", pa.int64()), ("text", pa.string()), ("ids", pa.list_(pa.int32())), *([("decoded", pa.string())] if back else [])])

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        found: list[pa.RecordBatch] = []
        places, bounds = right["place"].to_numpy(), right["bounds"].fill_null(-1).to_numpy()
        for docs in left["docs"]:
            table = pa.ipc.open_stream(docs.as_py()).read_all()
            units = Units.of(table["text"], pieces)
            # Parts to units to words: each step gathers bytes, and a row's ids are one slice of the last.
            linked = spelled(units.parts, places, bounds).take(units.links)
            ends = np.frombuffer(linked.buffers()[1], np.int64, len(linked) + 1, 8 * linked.offset)
            whole = pa.Array.from_buffers(pa.large_binary(), len(units.cuts) - 1, [None, pa.py_buffer(ends[units.cuts]), linked.buffers()[2]])
            every = whole.take(units.words)
            del linked, whole
            ends = np.frombuffer(every.buffers()[1], np.int64, len(every) + 1, 8 * every.offset)[units.rows] // kind.itemsize
            flat = np.frombuffer(every.buffers()[2], kind, int(ends[-1])) if len(ends) and ends[-1] else np.zeros(0, kind)
            known = table["text"].combine_chunks().is_null()
            known = known if isinstance(known, pa.Array) else pa.concat_arrays(known.chunks)
            ids = pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(flat.astype(np.int32)), mask=known)
            coded = pa.table({"doc_id": table["doc_id"].cast(pa.int64()), "text": table["text"].cast(pa.string()), "ids": ids}).combine_chunks()
            del units, every, flat
            # In small batches, so that neither side holds a block in several forms.
            found += [_with_texts(b, spelling, pieces.prefix) if back else b for b in coded.to_batches(max_chunksize=ROWS)]
        _release()
        return pa.Table.from_batches(found, schema)  # none where a repeated task cut the units otherwise: no documents have this name

    return run


def encode(docs: DataFrame, pieces: Pieces, back: bool = False) -> DataFrame:
    """doc_id, text, ids; with back also decoded, the text of ids."""
    parts = 8 * common.partitions(docs.sparkSession)  # a unit's edges are some hundred times the unit
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    listed = own.mapInArrow(_list_units(pieces), "block long not null, place int not null, unit string not null").repartition(parts, "unit")
    # All three columns are asked for and nothing is filtered before the grouping, so that the join below reads this same exchange.
    once = listed.groupBy("unit").agg(F.max("place").alias("p"), F.max("block").alias("b"), F.max(F.length("unit")).alias("n")).where("p >= 0 and b is not null")
    # A unit in which nothing joins has no bounds: all its characters are tokens.
    bounds = listed.join(unit_bounds(once.select("unit", "n"), pieces), "unit", "left").select("block", "place", "bounds")
    packs = own.mapInArrow(_pack, "block long, docs binary")
    out = "doc_id long, text string, ids array<int>" + ", decoded string" * back
    return packs.groupBy("block").cogroup(bounds.groupBy("block")).applyInArrow(_encode_block(pieces, back), out)


ROWS = 1000


def _with_texts(batch: pa.RecordBatch, spelling: pa.Array, prefix: bool) -> pa.RecordBatch:
    """batch with decoded: every id's bytes, one after another; a row's text is one slice of them."""
    lists = batch.column("ids")
    spelled = spelling.take(lists.flatten())
    ends = np.frombuffer(spelled.buffers()[1], np.int64) if len(spelled) else np.zeros(1, np.int64)
    data = memoryview(spelled.buffers()[2]) if len(spelled) and spelled.buffers()[2] is not None else memoryview(b"")
    sizes = lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
    at = ends[np.concatenate(([0], np.cumsum(sizes))).astype(np.int64)]
    texts = []
    for i, known in enumerate(lists.is_valid().to_pylist()):
        text = str(data[at[i] : at[i + 1]], "utf-8", "replace") if known else None
        texts.append(text[1:] if text and prefix and text[0] == " " else text)
    return pa.RecordBatch.from_arrays([*batch.columns, pa.array(texts, pa.string())], names=[*batch.schema.names, "decoded"])


def decode(encoded: DataFrame, pieces: Pieces) -> DataFrame:
    """encoded with decoded: the text of ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        spelling = pa.array(pieces.raw, pa.large_binary())
        for batch in (whole.slice(at, ROWS) for whole in batches for at in range(0, max(1, whole.num_rows), ROWS)):
            yield _with_texts(batch, spelling, pieces.prefix)

    from pyspark.sql import types as T

    own = encoded.drop("decoded")
    return own.mapInArrow(run, T.StructType([*own.schema.fields, T.StructField("decoded", T.StringType())]))


def op4_sentencepiece(spark, sf_dir: str, model: str = MODEL) -> DataFrame:
    """doc_id, n_pieces, ids_sha256 (ids joined by spaces), same_text: decoding gives the text back, space marks read as spaces."""
    pieces = Pieces.load(model)
    coded = encode(common.table(spark, sf_dir, "documents"), pieces, back=True)
    return coded.select(
        "doc_id",
        F.when(F.col("ids").isNull(), 0).otherwise(F.size("ids")).cast("long").alias("n_pieces"),
        F.sha2(F.coalesce(F.array_join(F.col("ids").cast("array<string>"), " "), F.lit("")), 256).alias("ids_sha256"),
        (F.coalesce("decoded", F.lit("")) == F.translate(F.coalesce("text", F.lit("")), MARK, " ")).alias("same_text"),
    )
