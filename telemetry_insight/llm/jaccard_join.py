"""Exact Jaccard self-join of word n-gram sets, size-aware: light sets by subsets, heavy sets by lists.

Sets that agree to at least `percent` / 100 share at least the ceiling o(n) of
that part of the larger one's n elements. In one global order of elements, two
such sets have a common element among their first n - o(n) + 1, and two common
elements among their first n - o(n) + 2. Light sets (at most `boundary`
elements) are matched by all 2-subsets of the longer prefix; heavy sets scan
the inverted lists of the single elements of the shorter prefix, in which light
sets near the boundary take part too. The boundary is the one of least cost:
subsets written for light sets against postings times the expected list length for heavy
ones. Elements go by how common they are in a fixed-size count sketch, then by
hash, so common passages come last; any order gives the same result.

Groups of copies never become all pairs. Equal sets are one class from the
start, and lists of the same classes are one list. Then rounds go over the lists
that hold several components: each class is paired with its nearest
of another component there, by parity maps that bound the difference of two sets;
the pairs are verified and join components. The first round looks at a
few heads of each list only, the second at every class. What may still link is
then sent as a forest, never as pairs: fewer rows than a list has classes. Classes
that it connects share a room, where each comes once with its text; the links that
join components are found there by comparing sets, so every pair that may
link is verified or connected, and components are exact. Long lists and rooms are cut
into blocks, and blocks meet pairwise, each in a task of bounded size.

Defined cases: words are runs without ASCII white space, A-Z lower-cased; a
text with fewer words than n is one element; null or empty texts have empty sets, which
link with nothing; rows that repeat a doc_id are one node with the links of all its texts; a null doc_id is left
without links. Elements and classes are 64-bit hashes.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common, wordhash
from .components import components

SKETCH_BITS, SEGMENTS = 21, 128
#: Places of a parity map, and of the map that each entry of a list carries.
LEAST_PLACES, LIST_PLACES, MOST_PLACES = 256, 1 << 12, 1 << 16
#: Places for each element, at least: the more, the fewer differences fall on one place and hide each other.
SPARE = 4
#: Rows of a list that one task compares with one another, and heads of a list in the first round.
LIST_BLOCK, HEADS = 4096, 16
#: Elements of the sets that a block of a room holds, at most or of one set.
ROOM_ELEMENTS = 1 << 20
_EMPTY = 0


def element_sets(texts: pa.Array, width: int) -> list[np.ndarray]:
    """The sorted distinct element hashes of each text."""
    words, ends = wordhash.word_hashes(texts, lower=True)
    hashes, _, ptr = wordhash.windows(words, ends, width)
    out = []
    for i in range(len(ends) - 1):
        a, b = ptr[i], ptr[i + 1]
        if a == b:
            own = words[ends[i] : ends[i + 1]]
            if len(own):
                whole, _, _ = wordhash.windows(own, np.array([0, len(own)]), len(own))
                out.append(wordhash.mix(whole + np.uint64(len(own))))
            else:
                out.append(own)
            continue
        s = np.sort(hashes[a:b])
        new = np.ones(len(s), bool)
        np.not_equal(s[1:], s[:-1], out=new[1:])
        out.append(s[new])
    return out


def class_id(s: np.ndarray) -> int:
    """A hash of the whole set; 0 for the empty set only."""
    if not len(s):
        return _EMPTY
    x = np.array([wordhash.mix(s ^ np.uint64(0x5851F42D4C957F2D)).sum(dtype=np.uint64) + np.uint64(len(s))], np.uint64)
    return int(wordhash.mix(x).view(np.int64)[0]) or 1


def parity_map(s: np.ndarray) -> bytes:
    """Which places an odd number of elements fall on: two maps differ in no more places than the sets do in elements.

    The places grow with the set, a power of two of them; halves of a map, one upon the other, are the map of half the places.
    """
    places = min(MOST_PLACES, max(LEAST_PLACES, SPARE << int(max(1, len(s)) - 1).bit_length()))
    odd = np.bincount(((s >> np.uint64(20)) & np.uint64(places - 1)).astype(np.int64), minlength=places) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def _map_bits(maps: list[bytes], size: int) -> np.ndarray:
    """Maps as rows of 64-bit words, folded to `size` bytes."""
    out = np.empty((len(maps), size // 8), np.uint64)
    for i, m in enumerate(maps):
        x = np.frombuffer(m, np.uint64)
        while len(x) > size // 8:
            x = x[: len(x) // 2] ^ x[len(x) // 2 :]
        out[i] = x
    return out


def _may_link(apart: np.ndarray, both: np.ndarray, percent: int) -> np.ndarray:
    """Whether sets that differ in `apart` places at least, of `both` elements together, can reach the similarity."""
    return apart * (100 + percent) <= (100 - percent) * both


def _need(n: int, percent: int) -> int:
    return -(-percent * n // 100)


def _reach(x: np.ndarray, y: np.ndarray, percent: int) -> bool:
    """Whether two sets reach the similarity."""
    if not len(x) or 100 * len(y) < percent * len(x) or 100 * len(x) < percent * len(y):
        return False
    at = np.searchsorted(x, y)
    at[at == len(x)] = 0
    both = int((x[at] == y).sum())
    return 100 * both >= percent * (len(x) + len(y) - both)


def forest(pairs: np.ndarray) -> np.ndarray:
    """Those of the pairs (rows of two) that connect what all of them connect, without cycles."""
    names, ends = np.unique(pairs, return_inverse=True)
    ends, label, left, kept = ends.reshape(pairs.shape), np.arange(len(names)), np.arange(len(pairs)), [np.zeros(0, np.int64)]
    while True:
        at = label[ends[left]]
        apart = at[:, 0] != at[:, 1]
        at, left = at[apart], left[apart]
        if not len(left):
            return pairs[np.concatenate(kept)]
        high, first = np.unique(at.max(1), return_index=True)  # each joins one lower label
        to = np.arange(len(names))
        to[high] = at[first].min(1)
        kept.append(left[first])
        while (to[to] != to).any():
            to = to[to]
        label = to[label]


def _describe(width: int):
    """doc_id, n, class and parity map of each document; at the end of a task, its counts of elements in sketch segments."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(1 << SKETCH_BITS, np.uint32)
        for batch in (x for whole in batches for x in wordhash.slices(whole)):
            sets = element_sets(batch.column("text"), width)
            every = np.concatenate(sets) if sets else np.zeros(0, np.uint64)
            counts += np.bincount((every >> np.uint64(64 - SKETCH_BITS)).astype(np.int64), minlength=1 << SKETCH_BITS).astype(np.uint32)
            rows = len(sets)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([len(s) for s in sets], pa.int64()), pa.array([class_id(s) for s in sets], pa.int64()), pa.array([parity_map(s) for s in sets], pa.binary()), pa.nulls(rows, pa.int32()), pa.nulls(rows, pa.binary())], names=_DESCRIBED)
        parts = counts.reshape(SEGMENTS, -1)
        if counts.any():
            yield pa.RecordBatch.from_arrays([pa.nulls(SEGMENTS, pa.int64()), pa.nulls(SEGMENTS, pa.int64()), pa.nulls(SEGMENTS, pa.int64()), pa.nulls(SEGMENTS, pa.binary()), pa.array(range(SEGMENTS), pa.int32()), pa.array([zlib.compress(p.tobytes(), 1) for p in parts], pa.binary())], names=_DESCRIBED)

    return run


_DESCRIBED = ["doc_id", "n", "class", "parity", "seg", "counts"]


def _add(table: pa.Table) -> pa.Table:
    total = sum(np.frombuffer(zlib.decompress(x.as_py()), np.uint32).astype(np.uint64) for x in table["counts"])
    packed = zlib.compress(np.minimum(total, np.iinfo(np.uint32).max).astype(np.uint32).tobytes(), 1)
    return pa.table({"seg": pa.array([table["seg"][0].as_py()], pa.int32()), "counts": pa.array([packed], pa.binary())})


def _sketch(described: DataFrame) -> np.ndarray:
    """The summed counts: a fixed 8 MB, whatever the corpus."""
    rows = described.where("seg is not null").select("seg", "counts").withColumn("part", F.pmod(F.xxhash64("counts"), F.lit(32)))
    once = rows.groupBy("seg", "part").applyInArrow(_add, "seg int, counts binary")
    got = {r["seg"]: r["counts"] for r in once.groupBy("seg").applyInArrow(_add, "seg int, counts binary").collect()}
    empty = zlib.compress(np.zeros((1 << SKETCH_BITS) // SEGMENTS, np.uint32).tobytes())
    return np.concatenate([np.frombuffer(zlib.decompress(bytes(got.get(i, empty))), np.uint32) for i in range(SEGMENTS)])


def choose_boundary(sizes: dict[int, int], list_length: float, percent: int, most: int = 64) -> int:
    """The largest light size: least cost of 2-subsets for light sets plus postings and their lists for heavy ones."""
    prefix = lambda n: n - _need(n, percent) + 1

    def cost(x: int) -> float:
        light = sum(c * prefix(n) * (prefix(n) + 1) / 2 for n, c in sizes.items() if n <= x)
        return light + sum(c * prefix(n) * (1 + list_length) for n, c in sizes.items() if 100 * n > percent * x)

    return min(range(1, most + 1), key=lambda x: (cost(x), x))


def _postings(width: int, percent: int, boundary: int, level: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (x for whole in batches for x in wordhash.slices(whole)):
            keys, sizes, owners, seen = [], [], [], set()
            for s in element_sets(batch.column("text"), width):
                n, own = len(s), class_id(s)
                if n < 2 or own in seen:
                    continue
                seen.add(own)
                p = n - _need(n, percent) + 1
                order = s[np.lexsort((s, level[(s >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)]))[: p + 1]]
                if n <= boundary:
                    i, j = np.triu_indices(len(order), 1)
                    keys.append(wordhash.mix(order[i] * np.uint64(0x9FB21C651E98DF25) + order[j]))
                    sizes.append(n)
                    owners.append((own, len(keys[-1])))
                if 100 * n > percent * boundary:
                    keys.append(order[:p])
                    sizes.append(n)
                    owners.append((own, len(keys[-1])))
            if keys:
                count = [c for _, c in owners]
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys).view(np.int64)), pa.array(np.repeat(np.array(sizes, np.int32), count)), pa.array(np.repeat(np.array([o for o, _ in owners], np.int64), count))], names=["key", "n", "class"])

    return run


def _shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From postings sorted by key, n, class: those whose key other classes have too, once each."""
    held = None  # the last posting, not sent yet: key, n, class, known to be shared
    for batch in batches:
        key, n, own = (batch.column(i).to_numpy() for i in range(3))
        if held is not None:
            key, n, own = (np.concatenate(([h], x)) for h, x in zip(held[:3], (key, n, own), strict=True))
        new = np.ones(len(key), bool)
        new[1:] = (key[1:] != key[:-1]) | (own[1:] != own[:-1])
        key, n, own = key[new], n[new], own[new]
        if not len(key):
            continue
        same = key[1:] == key[:-1]
        shared = np.zeros(len(key), bool)
        shared[1:] |= same
        shared[:-1] |= same
        shared[0] |= held is not None and held[3]
        held = key[-1], n[-1], own[-1], bool(shared[-1])
        out = np.flatnonzero(shared[:-1])
        if len(out):
            yield pa.RecordBatch.from_arrays([pa.array(key[out]), pa.array(n[out].astype(np.int32)), pa.array(own[out])], names=["key", "n", "class"])
    if held is not None and held[3]:
        yield pa.RecordBatch.from_arrays([pa.array([held[0]], pa.int64()), pa.array([held[1]], pa.int32()), pa.array([held[2]], pa.int64())], names=["key", "n", "class"])


def _classes(width: int):
    """class and text of documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (x for whole in batches for x in wordhash.slices(whole)):
            sets = element_sets(batch.column("text"), width)
            yield pa.RecordBatch.from_arrays([pa.array([class_id(s) for s in sets], pa.int64()), batch.column("text")], names=["class", "text"])

    return run


def _bounded(percent: int):
    """Pairs of classes with sizes and parity maps: those that may link, with the places they differ in."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            apart = []
            for x, y in zip(batch.column("a_parity").to_pylist(), batch.column("b_parity").to_pylist(), strict=True):
                u, v = _map_bits([x, y], min(len(x), len(y)))
                apart.append(int(np.bitwise_count(u ^ v).sum()))
            far = np.array(apart, np.int64)
            keep = np.flatnonzero(_may_link(far, batch.column("a_n").to_numpy() + batch.column("b_n").to_numpy(), percent))
            if len(keep):
                yield pa.RecordBatch.from_arrays([batch.column("a").take(pa.array(keep)), batch.column("b").take(pa.array(keep)), pa.array(far[keep])], names=["a", "b", "apart"])

    return run


def _verified(width: int, percent: int):
    """Pairs (a, b, a_text, b_text), sorted by a: those that reach the similarity."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, known = None, None
        for batch in (x for whole in batches for x in wordhash.slices(whole, "b_text")):
            a, b = batch.column("a").to_pylist(), batch.column("b").to_pylist()
            others = element_sets(batch.column("b_text"), width)
            keep = []
            for i, s in enumerate(others):
                if a[i] != last:
                    last, known = a[i], element_sets(batch.column("a_text").slice(i, 1), width)[0]
                if _reach(known, s, percent):
                    keep.append(i)
            if keep:
                yield pa.RecordBatch.from_arrays([pa.array([a[i] for i in keep], pa.int64()), pa.array([b[i] for i in keep], pa.int64())], names=["a", "b"])

    return run


def _links(pairs: DataFrame, texts: DataFrame, width: int, percent: int) -> DataFrame:
    """The pairs (a, b) of classes that link. The larger group's text is met in order, so a leader's set is made once a run."""
    lean = texts.select("class", "text")
    held = pairs.join(lean.select(F.col("class").alias("b"), F.col("text").alias("b_text")), "b").join(lean.select(F.col("class").alias("a"), F.col("text").alias("a_text")), "a")
    return held.sortWithinPartitions("a").select("a", "b", "a_text", "b_text").mapInArrow(_verified(width, percent), "a long, b long")


def _whole_cells(batches: Iterator[pa.RecordBatch]) -> Iterator[dict[str, np.ndarray]]:
    """Columns of rows sorted by cell, in portions that end where a cell ends."""
    rest: pa.Table | None = None
    for batch in chain(batches, [None]):
        if batch is not None:
            here = pa.Table.from_batches([batch])
            rest = here if rest is None else pa.concat_tables([rest, here])
            cells = rest["cell"].to_numpy()
            cut = int(np.flatnonzero(cells == cells[-1])[0]) if len(cells) else 0
            now, rest = rest.slice(0, cut), rest.slice(cut)
        elif rest is not None:
            now, rest = rest, None
        else:
            return
        if now.num_rows:
            yield {c: now[c].to_numpy() for c in now.column_names} | {"places": 8 * pc.binary_length(now["parity"]).to_numpy().astype(np.int64)}


def _near_pairs(percent: int, few: int, heads: int):
    """From the classes of cells: each with its nearest `few` of other components that it may link with; or, with few 0, a forest of all that may link.

    A cell holds a block of a list (side 0), or two blocks of one that meet (sides 0 and 1). With heads, long cells are compared with so many of their rows only.
    Sets that may link have maps of one size or of one and its double: each size is compared at its own level, with the doubles folded.
    """

    def nearest(n: np.ndarray, comp: np.ndarray, side: np.ndarray, double: np.ndarray, bits: np.ndarray, to: np.ndarray, of: np.ndarray) -> tuple[np.ndarray, ...]:
        """For m cells of equal size (m x size arrays), the rows `of` against the rows `to`: indices of cell, row and other."""
        apart = np.zeros((len(n), len(of), len(to)), np.int32)
        for w in range(bits.shape[2]):
            word = bits[:, :, w]
            apart += np.bitwise_count(word[:, of][:, :, None] ^ word[:, to][:, None, :])
        x, y = n[:, of, None], n[:, None, to]
        ok = (comp[:, of, None] != comp[:, None, to]) & (100 * np.minimum(x, y) >= percent * np.maximum(x, y)) & _may_link(apart, x + y, percent)
        two = (side.max(1) != side.min(1))[:, None, None]
        ok &= ~two | (side[:, of, None] != side[:, None, to])
        ok &= ~(double[:, of, None] & double[:, None, to])
        if not few or few >= apart.shape[2]:
            cell, row, other = np.nonzero(ok)
            return cell, of[row], other
        apart[~ok] = np.iinfo(np.int32).max
        best = np.argpartition(apart, few - 1, axis=2)[:, :, :few]
        cell, row, k = np.nonzero(np.take_along_axis(ok, best, 2))
        return cell, of[row], best[cell, row, k]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = []

        def sent() -> pa.RecordBatch:
            every = np.concatenate(found)
            if not heads:  # only then the direction says nothing
                every.sort(axis=1)
            every = np.unique(every, axis=0) if few else forest(every)
            found.clear()
            return pa.RecordBatch.from_arrays([pa.array(every[:, 0]), pa.array(every[:, 1])], names=["a", "b"])

        def level(col: dict[str, np.ndarray], places: int) -> Iterator[None]:
            """Compare the rows whose maps have so many places, or twice as many."""
            here = np.flatnonzero((col["places"] == places) | (col["places"] == 2 * places))
            cells, sizes_of = col["cell"][here], col["places"][here]
            begins = np.flatnonzero(np.concatenate(([True], cells[1:] != cells[:-1])))
            sizes = np.diff(np.append(begins, len(here)))
            bits = _map_bits(col["parity"][here].tolist(), places // 8)
            words = bits.shape[1]
            for size in np.unique(sizes[sizes > 1]).tolist():
                starts = begins[sizes == size]
                wide = heads if heads and size > 4 * heads else size
                most = max(1 << 14, (1 << 21) // words)
                rows, step = max(1, min(size, most // wide)), max(1, most // (size * max(wide, words))) if wide == size else 1
                for at in range(0, len(starts), step):
                    index = starts[at : at + step, None] + np.arange(size)
                    n, comp, side, own = (col[c][here[index]] for c in ("n", "component", "side", "class"))
                    if (comp == comp[:, :1]).all():
                        continue
                    to = np.sort(np.argsort(wordhash.mix(own[0].view(np.uint64)), kind="stable")[:wide])  # the same heads in lists of nearly the same classes
                    for lo in range(0, size, rows):
                        cell, row, other = nearest(n.astype(np.int64), comp, side, sizes_of[index] > places, bits[index], to, np.arange(lo, min(size, lo + rows)))
                        if len(cell):
                            pairs = np.column_stack([own[cell, row], own[cell, to[other]]])
                            found.append(pairs if few else forest(pairs))
                    if sum(map(len, found)) > 200_000:
                        yield

        for col in _whole_cells(batches):
            for places in np.unique(col["places"]).tolist():
                for _ in level(col, places):
                    yield sent()
        if found:
            yield sent()

    return run


def _settled(width: int, percent: int):
    """From the classes of rooms with their texts, sorted by cell: links (a, b) that join all components which links join there, without cycles.

    A cell holds a block of a room (side 0), or two blocks of one that meet (sides 0 and 1).
    """

    def settle(rows: list[tuple]) -> np.ndarray:
        side, own, comp = (np.array(x, np.int64) for x in list(zip(*rows, strict=True))[:3])
        sets, out = [x[3] for x in rows], []
        root = np.unique(comp, return_inverse=True)[1].reshape(-1)
        n, maps = np.array([len(s) for s in sets], np.int64), [parity_map(s) for s in sets]
        sizes = np.array([8 * len(m) for m in maps])
        two = side.max() != side.min()
        for places in np.unique(sizes).tolist():
            here = np.flatnonzero((sizes == places) | (sizes == 2 * places))
            bits = _map_bits([maps[i] for i in here], places // 8)
            for k, i in enumerate(here[:-1].tolist()):
                rest = here[k + 1 :]
                look = np.flatnonzero((root[rest] != root[i]) & (100 * np.minimum(n[rest], n[i]) >= percent * np.maximum(n[rest], n[i])) & ((sizes[i] == places) | (sizes[rest] == places)) & (not two or side[rest] != side[i]))
                apart = np.bitwise_count(bits[k + 1 + look] ^ bits[k]).sum(1, dtype=np.int64)
                look, apart = (x[_may_link(apart, n[rest[look]] + n[i], percent)] for x in (look, apart))
                for j in rest[look[np.argsort(apart, kind="stable")]].tolist():
                    if root[i] != root[j] and _reach(sets[i], sets[j], percent):
                        root[root == root[j]] = root[i]
                        out.append((own[i], own[j]))
        return np.sort(np.array(out, np.int64).reshape(-1, 2), axis=1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cell, rows = None, []
        for batch in chain((x for whole in batches for x in wordhash.slices(whole)), [None]):
            new = zip(*(batch.column(c).to_pylist() for c in ("cell", "side", "class", "component")), element_sets(batch.column("text"), width), strict=True) if batch is not None else [(None,)]
            for at, *row in new:
                if at != cell:
                    if len(rows) > 1 and len(links := settle(rows)):
                        yield pa.RecordBatch.from_arrays([pa.array(links[:, 0]), pa.array(links[:, 1])], names=["a", "b"])
                    cell, rows = at, []
                rows.append(row)

    return run


def near_components(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id: the set's size and the smallest doc_id reachable over links of at least percent / 100."""
    spark = docs.sparkSession
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    described = common.stored(spark, texts.mapInArrow(_describe(width), "doc_id long, n long, class long, parity binary, seg int, counts binary"), "sets")
    sets = described.where("n is not null").select("doc_id", "n", "class")
    # The order of elements, and the boundary between light and heavy sets.
    sketch = _sketch(described)
    mean = max(1.0, float(sketch.mean()))
    level = np.minimum(255, 8 * np.log2(1 + sketch / mean)).astype(np.uint8)
    excess = max(0.0, float((sketch.astype(float) ** 2).sum() / max(1, sketch.sum(dtype=np.int64)) - mean))
    sizes = {r["n"]: r["c"] for r in sets.where("n between 2 and 200").groupBy("n").agg(F.count(F.lit(1)).alias("c")).collect()}
    boundary = choose_boundary(sizes, min(excess, 64.0), percent)
    # Candidate lists.
    named = texts.where(F.col("doc_id").isNotNull() & (F.length("text") > 0))
    postings = named.select("text").mapInArrow(_postings(width, percent, boundary, level), "key long, n int, class long")
    parts = common.partitions(spark)
    every = common.stored(spark, postings.repartition(parts, "key").sortWithinPartitions("key", "n", "class").mapInArrow(_shared, "key long, n int, class long"), "lists")
    # Lists of the same classes say the same: one of them stays.
    marks = every.groupBy("key").agg(F.sum(F.xxhash64("class").cast("decimal(38,0)")).alias("h"), F.count(F.lit(1)).alias("c"))
    alone = marks.groupBy("h", "c").agg(F.min("key").alias("key")).select("key", F.ceil(F.col("c") / LIST_BLOCK).cast("int").alias("blocks"))
    own = every.join(common.stored(spark, alone, "lists"), "key")
    classes = described.where("n > 0 and doc_id is not null").groupBy("class").agg(F.min("doc_id").alias("doc_id"), F.first("n").alias("n"), F.first("parity").alias("parity"))
    classes = common.stored(spark, classes.join(own.select("class").distinct(), "class", "left_semi"), "classes")
    maps = classes.select("class", "parity").mapInArrow(_folded, "class long, parity binary")
    lists = common.stored(spark, own.join(maps, "class").select("key", "blocks", "n", "class", "parity"), "lists")

    def texts_of(asked: DataFrame) -> DataFrame:
        """class and text of the classes asked for, and maybe of others."""
        holders = common.stored(spark, classes.join(asked, "class", "left_semi").select("doc_id").distinct(), "holders")
        found = named.join(holders, "doc_id", "left_semi").select("text").mapInArrow(_classes(width), "class long, text string").dropDuplicates(["class"])
        return common.stored(spark, found, "candidates")

    def links(pairs: DataFrame) -> DataFrame:
        """The pairs (a, b) that link, from the texts of their classes."""
        texts = texts_of(pairs.select(F.col("a").alias("class")).union(pairs.select(F.col("b").alias("class"))).distinct())
        with common.arrow_rows(spark, 64):  # rows of two whole texts
            return common.stored(spark, _links(pairs, texts, width, percent), "links")

    def room_links(rooms: DataFrame, labels: DataFrame) -> DataFrame:
        """Links that join the components of each room (class, room), from one row a class and block."""
        rooms = rooms.join(classes.select("class", "n"), "class")
        blocks = rooms.groupBy("room").agg(F.greatest(F.ceil(F.sum("n") / ROOM_ELEMENTS), F.ceil(F.count(F.lit(1)) / LIST_BLOCK)).cast("int").alias("blocks"))
        dealt = rooms.join(blocks, "room").join(labels, "class", "left").withColumn("component", F.coalesce("component", "class")).withColumn("block", F.pmod(F.xxhash64("class", F.lit(5)), F.col("blocks")).cast("int"))
        dealt = dealt.withColumn("with", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
        cell = F.xxhash64("room", F.least("block", "with"), F.greatest("block", "with"))
        dealt = dealt.select(cell.alias("cell"), (F.col("block") > F.col("with")).cast("int").alias("side"), "class", "component")
        held = dealt.join(texts_of(rooms.select("class")), "class").repartition(parts, "cell").sortWithinPartitions("cell")
        with common.arrow_rows(spark, 64):  # rows of whole texts
            return common.stored(spark, held.mapInArrow(_settled(width, percent), "a long, b long"), "links")

    def cells(labels: DataFrame, cut: bool) -> DataFrame:
        """The lists by cell: blocks of a list, and if cut also every two blocks of it. Cells of one component are passed over where they are read."""
        apart = lists.join(labels, "class", "left").withColumn("component", F.coalesce("component", "class")).withColumn("block", F.pmod(F.xxhash64("class", F.lit(5)), F.col("blocks")).cast("int"))
        apart = apart.withColumn("with", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)) if cut else F.col("block"))
        cell = F.xxhash64("key", F.least("block", "with"), F.greatest("block", "with"))
        dealt = apart.select(cell.alias("cell"), (F.col("block") > F.col("with")).cast("int").alias("side"), "n", "class", "component", "parity")
        return dealt.repartition(parts, "cell").sortWithinPartitions("cell", "n", "class")

    # Texts of one doc_id are one node.
    ids = sets.where("n > 0 and doc_id is not null")
    several = ids.groupBy("doc_id").agg(F.min("class").alias("a"), F.max("class").alias("b")).where("a < b").select("doc_id", "a")
    joined = common.stored(spark, ids.join(several, "doc_id").select("a", F.col("class").alias("b")), "links")
    labels = components(joined).withColumnRenamed("node", "class")
    tested = None
    for heads in (HEADS, 0):
        found = cells(labels, not heads).mapInArrow(_near_pairs(percent, 1, heads), "a long, b long")
        # Stored once each: Spark would move an anti-join below a distinct, to the pairs as often as lists repeat them.
        pairs = common.stored(spark, found.distinct(), "near")
        if tested is not None:
            pairs = pairs.join(tested, ["a", "b"], "left_anti")
        side = lambda c: classes.select(F.col("class").alias(c), F.col("n").alias(f"{c}_n"), F.col("parity").alias(f"{c}_parity"))
        bounded = pairs.join(side("a"), "a").join(side("b"), "b").mapInArrow(_bounded(percent), "a long, b long, apart long")
        if heads:
            bounded = bounded.groupBy("a").agg(F.min(F.struct("apart", "b")).alias("best")).select("a", F.col("best.b").alias("b"))
        tested = common.stored(spark, bounded.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "pairs")
        if not tested.isEmpty():
            labels = _merged(labels, links(tested))
    near = common.stored(spark, cells(labels, True).mapInArrow(_near_pairs(percent, 0, 0), "a long, b long").distinct(), "near")
    if not near.isEmpty():
        rooms = components(near).select(F.col("node").alias("class"), F.col("component").alias("room"))
        labels = _merged(labels, room_links(rooms, labels))
    return _labelled(sets, labels)


def _folded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Classes with maps of at most LIST_PLACES places."""
    for batch in batches:
        maps = [m if 8 * len(m) <= LIST_PLACES else _map_bits([m], LIST_PLACES // 8)[0].tobytes() for m in batch.column("parity").to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column("class"), pa.array(maps, pa.binary())], names=["class", "parity"])


def _merged(labels: DataFrame, links: DataFrame) -> DataFrame:
    """class, component after more links (a, b): only the components that they join are worked on."""
    spark = links.sparkSession
    of = lambda c: labels.select(F.col("class").alias(c), F.col("component").alias(f"{c}_component"))
    ends = links.join(of("a"), "a", "left").join(of("b"), "b", "left").select(F.coalesce("a_component", "a").alias("a"), F.coalesce("b_component", "b").alias("b"))
    joined = components(ends).select(F.col("node").alias("component"), F.col("component").alias("now"))
    old = labels.join(joined, "component", "left").select("class", F.coalesce("now", "component").alias("component"))
    new = joined.select(F.col("component").alias("class"), F.col("now").alias("component")).join(labels, "class", "left_anti")
    return common.stored(spark, old.union(new), "labels")


def _labelled(sets: DataFrame, labels: DataFrame) -> DataFrame:
    """Documents with the smallest doc_id of their component; empty sets stand alone."""
    spark = sets.sparkSession
    group = sets.join(labels, "class", "left").select("doc_id", "n", F.when(F.col("n") > 0, F.coalesce("component", "class")).alias("grp"))
    group = common.stored(spark, group, "groups")
    least = common.stored(spark, group.where("grp is not null and doc_id is not null").groupBy("grp").agg(F.min("doc_id").alias("least"), F.count(F.lit(1)).alias("c")).where("c > 1"), "least")
    return group.join(least, "grp", "left").select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), F.coalesce("least", "doc_id")).alias("component_id"))


def op9_jaccard_join(spark, sf_dir: str) -> DataFrame:
    return near_components(common.table(spark, sf_dir, "documents"))


OP9_SQL = """
WITH d AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS w FROM documents
), g AS (
  SELECT DISTINCT doc_id, array_to_string(w[i:i + 4], ' ') AS k FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, CASE WHEN len(w) > 0 THEN 2 ELSE 1 END))) AS i FROM d)
), n AS (
  SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id
), link AS (
  SELECT a, b FROM (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS common FROM g x JOIN g y ON x.k = y.k AND x.doc_id <> y.doc_id GROUP BY 1, 2) p
  JOIN n nx ON nx.doc_id = a JOIN n ny ON ny.doc_id = b WHERE 100 * common >= 80 * (nx.n + ny.n - common)
), reach AS (
  WITH RECURSIVE r(doc_id, root) AS (
    SELECT doc_id, doc_id FROM d UNION SELECT link.b, r.root FROM r JOIN link ON link.a = r.doc_id AND r.root < link.b
  ) SELECT doc_id, min(root) AS component_id FROM r GROUP BY doc_id
)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, component_id FROM d LEFT JOIN n USING (doc_id) JOIN reach USING (doc_id)
"""
