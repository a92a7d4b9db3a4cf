"""Groups of documents whose word shingles overlap, found without loss by an index over each text's rarest shingles.

Of two sets of shingles in one fixed order, with a similarity of t at least, the first n - ceil(t * n) + 1 shingles of each
(n its size) have one in common. So a text is indexed under those alone, and texts that meet under a shingle are all the candidates
there can be. The order has the shingles that are common in a sample of the texts last; the sample decides what the search costs, and
never what it finds.

Candidates are taken in three passes, so that a large group of near copies doesn't make all its pairs. The first compares each text
of a shingle's stretch with its neighbour in order of size and with the first of about its size; what is verified makes groups. The second
compares each text with one of another group, for what the first left beside a large one. The third compares all pairs of the stretch whose
groups differ, and leaves none out. All that meets is verified on whole texts, but for pairs that differ in more bits of their
``parities`` than sets of that similarity can.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Workspace, few_files, lean, row_count, small_batches, texts
from .components import components
from .rolling import Words, grouped

BUFFER = 1 << 19
LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
SAMPLE = 20_000  # texts whose shingles are counted for the order
COMMON = 1 << 16  # shingles that are known as common ones
BLOCK = 2048  # rows of a stretch that meet each other in one piece of work
PAIRS = 1 << 18  # pairs that are held at once
BRIEF = 512  # bytes of parities that travel with a row of the index
LISTED = 1 << 20  # most ids that are broadcast
SLACK = 1e-9


def _split(text: bytes) -> list[bytes]:
    return text.translate(LOWER).split()


def _sets(some: list[bytes], width: int):
    """Words, word hashes and for each text the sorted distinct hashes of its runs of ``width`` words, or of the whole if it has fewer."""
    split = [_split(t) for t in some]
    words = Words(split)
    place, runs = words.windows(words.hashes(), width)
    bounds = np.searchsorted(place, words.first)
    same = words.documents()
    lists = [np.unique(runs[a:b]).view(np.int64) if len(w) >= width else same[0][d : d + 1] for d, (a, b, w) in enumerate(zip(bounds, bounds[1:], split))]
    return words, same, lists


def parities(s: np.ndarray) -> np.ndarray:
    """Bits, a power of two of them and two for each shingle at least: how often, modulo 2, shingles fall on each."""
    size = max(64, 1 << int(2 * len(s)).bit_length())
    return np.packbits((np.bincount(s & (size - 1), minlength=size) & 1).astype(bool), bitorder="little")


def _apart(a: np.ndarray, b: np.ndarray) -> int:
    """Bits in which two of ``parities`` differ: never more than shingles that one of the sets has and the other lacks."""
    while len(a) > len(b):
        a = a[: len(a) // 2] ^ a[len(a) // 2 :]
    while len(b) > len(a):
        b = b[: len(b) // 2] ^ b[len(b) // 2 :]
    return int(np.bitwise_count(a ^ b).sum())


def _folded(a: np.ndarray, size: int) -> np.ndarray:
    """Parities, or rows of them, in ``size`` bytes at most."""
    while a.shape[-1] > size:
        half = a.shape[-1] // 2
        a = a[..., :half] ^ a[..., half:]
    return a


def _most(similarity: float, n, m):
    """How many shingles two sets of n and m of that similarity can differ in."""
    return (n + m) * (1 - similarity) / (1 + similarity) + SLACK


def _near(similarity: float, bits: np.ndarray, n: np.ndarray):
    """Tells of pairs of rows, by their places, whether the parities ``bits`` of the sets leave the similarity possible."""
    width = np.array([len(b) for b in bits], dtype=np.int64)
    made: dict[int, np.ndarray] = {}

    def table(size: int) -> np.ndarray:
        if size not in made:
            made[size] = np.zeros((len(bits), size), dtype=np.uint8)
            for w in np.unique(width[width >= size]):
                at = np.flatnonzero(width == w)
                made[size][at] = _folded(np.frombuffer(b"".join(bits[at]), dtype=np.uint8).reshape(-1, w), size)
        return made[size]

    def near(left: np.ndarray, right: np.ndarray) -> np.ndarray:
        keep, least = np.zeros(len(left), dtype=bool), np.minimum(width[left], width[right])
        for size in np.unique(least):
            whole = np.flatnonzero(least == size)
            for part in np.array_split(whole, -(-len(whole) * int(size) >> 24) or 1):
                a, b = left[part], right[part]
                keep[part] = np.bitwise_count(table(int(size))[a] ^ table(int(size))[b]).sum(axis=1, dtype=np.int64) <= _most(similarity, n[a], n[b])
        return keep

    return near


def _close(similarity: float):
    """Keeps pairs (a, b, n and bits of both) whose parities don't rule out the similarity."""

    def run(batches):
        for batch in batches:
            sizes = [batch.column(i).to_numpy() for i in (2, 3)]
            bits = [[np.frombuffer(x.as_buffer(), dtype=np.uint8) for x in batch.column(i)] for i in (4, 5)]
            most = _most(similarity, *sizes)
            keep = np.array([_apart(x, y) <= m for x, y, m in zip(*bits, most)], dtype=bool)
            yield batch.select([0, 1]).filter(pa.array(keep))

    return run


def _shingles(width: int):
    """(node, text) to its set of shingles."""

    def run(batches):
        for batch in batches:
            at = 0
            for some in grouped(texts(batch.column(1)), len, BUFFER):
                _, _, lists = _sets(some, width)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, len(some)), pa.array(lists, pa.list_(pa.int64()))], names=["node", "s"])
                at += len(some)

    return run


def _prints(width: int, similarity: float, common: np.ndarray, counts: np.ndarray):
    """(doc_id, text) to both halves of the word sequence's digest, the size of the set of shingles, its parities, and the
    shingles to index."""

    def first(s: np.ndarray) -> np.ndarray:
        kept = len(s) - math.ceil(similarity * len(s) - SLACK) + 1
        at = np.minimum(np.searchsorted(common, s), max(len(common) - 1, 0))
        known = np.where(common[at] == s, counts[at], 0) if len(common) else np.zeros(len(s), dtype=np.int64)
        return s[np.lexsort((s, known))[:kept]]

    def run(batches):
        for batch in batches:
            at = 0
            for some in grouped(texts(batch.column(1)), len, BUFFER):
                words, same, lists = _sets(some, width)
                bits = [parities(s) for s in lists]
                columns = [*map(pa.array, same), pa.array(np.diff(words.first)), pa.array([len(s) for s in lists], pa.int64()), pa.array([b.tobytes() for b in bits], pa.binary()), pa.array([_folded(b, BRIEF).tobytes() for b in bits], pa.binary()), pa.array([first(s) for s in lists], pa.list_(pa.int64()))]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, len(some)), *columns], names=["doc_id", "same1", "same2", "n_words", "n", "bits", "brief", "keys"])
                at += len(some)

    return run


def _sized(similarity: float, n, m):
    return np.minimum(n, m) >= similarity * np.maximum(n, m) - SLACK


def _may(similarity: float, n, pos, m, at):
    """Whether sets of n and m shingles that meet in their places pos and at, and in none before, can overlap enough."""
    return _sized(similarity, n, m) & (np.minimum(n - pos, m - at) >= similarity / (1 + similarity) * (n + m) - SLACK)


def _stretches(similarity: float):
    """Rows (key, n, node, pos) in order, without those whose key has no other row. ``head`` and ``prev`` are the first text
    of about the row's size and the one before it in its stretch, where the sizes allow it and else the row's own node."""
    step = math.log(1 / similarity)

    def emit(key, n, node, pos, head, keep):
        i = np.flatnonzero(keep)
        prev = np.maximum(i - 1, 0)
        out = []
        for other, apt in ((head[i], head[i] >= 0), (prev, key[prev] == key[i])):
            good = apt & _sized(similarity, n[i], n[other])
            out.append(np.where(good, node[other], node[i]))
        names = ["key", "n", "node", "pos", "head", "prev"]
        return pa.RecordBatch.from_arrays([pa.array(x) for x in (key[i], n[i], node[i], pos[i], *out)], names=names)

    def run(batches):
        held = None  # the head of the open group, the row before the last, and the last row, which isn't out yet
        for batch in batches:
            rows = [batch.column(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in range(4)]
            if not len(rows[0]):
                continue
            fixed = 0 if held is None else 2
            if held is not None:
                rows = [np.concatenate([h, x]) for h, x in zip(held, rows)]
            key, n, node, pos = rows
            size = np.floor(np.log(np.maximum(n, 1)) / step)
            new = np.concatenate([[True], (key[1:] != key[:-1]) | (size[1:] != size[:-1])])
            if fixed:  # the carried head may be far from the row before the last
                new[1], new[2] = True, new[2] or (key[0], size[0]) != (key[2], size[2])
            head = np.maximum.accumulate(np.where(new, np.arange(len(key)), 0))
            if fixed and not new[2]:
                head[2:] = np.where(head[2:] == 1, 0, head[2:])
            same = key[1:] == key[:-1]
            keep = np.concatenate([[False], same]) | np.concatenate([same, [False]])
            keep[:fixed] = False
            keep[-1] = False
            yield emit(key, n, node, pos, head, keep)
            last = len(key) - 1
            ends = [int(head[last]), last - 1 if last else last, last]
            if not last:  # nothing before the last row: a row of no key stands in
                held = [np.array([x[0], x[0], x[0]]) for x in rows]
                held[0][1] = ~held[0][1]
            else:
                held = [x[ends] for x in rows]
        if held is not None:
            key, n, node, pos = held
            keep = np.array([False, False, key[1] == key[2]])
            yield emit(key, n, node, pos, np.array([-1, -1, 0 if key[0] == key[2] else -1]), keep)

    return run


def _crossings(similarity: float, every: bool):
    """Rows (key, p, q, comp, blk, n, node, pos, brief) in order: all pairs of a stretch (key, p, q) whose groups differ and that can be
    similar by their sizes, places and parities, so that texts with nothing but a shingle in common make no rows. A stretch of
    two blocks makes only the pairs between them. Without ``every``, one such pair a row at most."""

    def pairs(rows):
        key, p, q, comp, blk, n, node, pos, *brief = rows
        near = _near(similarity, brief[0], n) if brief else lambda left, right: True
        start = np.flatnonzero(np.concatenate([[True], (key[1:] != key[:-1]) | (p[1:] != p[:-1]) | (q[1:] != q[:-1])]))
        run = np.concatenate([[True], comp[1:] != comp[:-1]])
        run[start] = True
        runs = np.flatnonzero(run)
        before, after = runs[np.cumsum(run) - 1], np.append(runs[1:], len(key))[np.cumsum(run) - 1]  # where the group starts, and the next one
        end = np.append(start[1:], len(key))[np.searchsorted(start, np.arange(len(key)), side="right") - 1]
        if not every:
            at = start[np.searchsorted(start, np.arange(len(key)), side="right") - 1]
            turned = (node.astype(np.uint64) ^ key.astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(33)
            outside = end - at - (after - before)  # rows of other groups; those after the own group come first
            other = after + turned.astype(np.int64) % np.maximum(outside, 1)
            other = np.where(other < end, other, other - end + at)
            good = (outside > 0) & _sized(similarity, n, n[np.minimum(other, len(key) - 1)])
            good[good] = near(np.flatnonzero(good), other[good])
            a, b = node[good], node[other[good]]
            yield np.column_stack([np.minimum(a, b), np.maximum(a, b)])
            return
        many = end - after
        total = np.cumsum(many)
        at = 0
        while at < len(key):
            to = max(at + 1, int(np.searchsorted(total, (total[at - 1] if at else 0) + PAIRS, side="right")))
            left = np.repeat(np.arange(at, to), many[at:to])
            if len(left):
                right = after[left] + np.arange(len(left)) - np.repeat(np.cumsum(many[at:to]) - many[at:to], many[at:to])
                good = _may(similarity, n[left], pos[left], n[right], pos[right]) & ((p[left] == q[left]) | (blk[left] != blk[right]))
                good[good] = near(left[good], right[good])
                a, b = node[left[good]], node[right[good]]
                yield np.column_stack([np.minimum(a, b), np.maximum(a, b)])
            at = to

    def run(batches):
        held = None
        for batch in batches:
            rows = [batch.column(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in range(8)]
            rows += [batch.column(i).to_numpy(zero_copy_only=False) for i in range(8, batch.num_columns)]
            if held is not None:
                rows = [np.concatenate([h, x]) for h, x in zip(held, rows)]
            if not len(rows[0]):
                continue
            last = np.flatnonzero((rows[0] == rows[0][-1]) & (rows[1] == rows[1][-1]) & (rows[2] == rows[2][-1]))[0]
            held = [x[last:] for x in rows]
            if last:
                for found in pairs([x[:last] for x in rows]):
                    yield _pairs(found)
        if held is not None:
            for found in pairs(held):
                yield _pairs(found)

    return run


def _pairs(found: np.ndarray) -> pa.RecordBatch:
    found = np.unique(found, axis=0) if len(found) else found
    return pa.RecordBatch.from_arrays([pa.array(found[:, 0]), pa.array(found[:, 1])], names=["a", "b"])


def similar_groups(spark, docs: DataFrame, similarity: float = 0.8, width: int = 5) -> DataFrame:
    """doc_id, component_id for every row of ``docs`` with a doc_id; component_id is the smallest doc_id reachable over links.

    Texts of one word sequence (A-Z lower-cased, split at ASCII white space) are one class, so null, empty and blank
    texts are one too; other classes are linked when the Jaccard similarity of their sets of ``width``-word shingles is
    ``similarity`` at least. All such links are found. A doc_id that repeats with different texts has the links of all of them. Rows without doc_id are left out. Repeated rows come as often as in ``docs``.
    An empty table gives an empty result. Other columns are ignored.
    """
    if not 0 < similarity < 1:
        raise ValueError("similarity must be over 0 and under 1")
    small_batches(spark)
    work = Workspace(spark, "similar")
    rows = row_count(docs)
    plain = docs.select("doc_id", "text").where("doc_id is not null")
    common, counts = _common(plain, width, rows)
    print_type = "doc_id long, same1 long, same2 long, n_words long, n long, bits binary, brief binary, keys array<long>"
    prints = work.put(plain.mapInArrow(lean(_prints(width, similarity, common, counts)), print_type), "prints", rows, exchange=True)
    classes = prints.groupBy("same1", "same2").agg(F.min("doc_id").alias("head"))
    members = work.put(prints.select("doc_id", "same1", "same2").join(classes, ["same1", "same2"]).select("doc_id", "head"), "members", rows)
    heads = prints.join(classes.select(F.col("head").alias("doc_id"), "same1", "same2"), ["doc_id", "same1", "same2"], "left_semi").where("n_words > 0")
    if heads.groupBy("doc_id").agg(F.count(F.lit(1)).alias("c")).where("c > 1").limit(1).count():
        heads = heads.dropDuplicates(["doc_id", "same1", "same2"])
    bits = work.put(heads.select(F.col("doc_id").alias("node"), "n", "bits", "brief"), "bits", rows)
    index = heads.select(F.col("doc_id").alias("node"), F.col("n").cast("int").alias("n"), F.posexplode("keys").alias("pos", "key"))
    index = index.select("key", "n", "node", "pos").repartition("key").sortWithinPartitions("key", "n", "node")
    index = work.put(index.mapInArrow(lean(_stretches(similarity)), "key long, n long, node long, pos long, head long, prev long"), "index", rows, each=2_500)
    work.drop("prints")  # what is left to do reads the members, the bits and the index
    first = index.select("node", F.explode(F.array("head", "prev")).alias("other")).where("node <> other")
    met = work.put(first.select(F.least("node", "other").alias("a"), F.greatest("node", "other").alias("b")).distinct(), "met-0", rows, each=2_500)
    links = _verified(plain, bits, met, similarity, width, work, "0", rows)
    for turn, every in (("1", False), ("2", True)):
        dealt = _dealt(index, components(links, Workspace(spark, "similar"), rows), bits.select("node", "brief"))
        rest = dealt.mapInArrow(lean(_crossings(similarity, every)), "a long, b long").distinct().join(met, ["a", "b"], "left_anti")
        more = work.put(rest, f"met-{turn}", rows, each=2_500)
        links = links.union(_verified(plain, bits, more, similarity, width, work, turn, rows))
        met = met.union(more)
    found = components(links, Workspace(spark, "similar"), rows)
    out = members.join(found, F.col("head") == F.col("node"), "left").select("doc_id", F.coalesce("component", "head").alias("component_id"))
    return few_files(out, rows)


def _dealt(index: DataFrame, found: DataFrame, brief: DataFrame) -> DataFrame:
    """The rows of ``index`` in stretches of more than one group, in order. Long stretches are dealt out by pairs of blocks."""
    rows = index.select("key", "n", "node", "pos").join(found, "node", "left").withColumn("comp", F.coalesce("component", "node"))
    mixed = rows.groupBy("key").agg(F.count(F.lit(1)).alias("c"), F.min("comp").alias("x"), F.max("comp").alias("y")).where("x <> y")
    mixed = mixed.select("key", F.ceil(F.col("c") / BLOCK).cast("int").alias("blocks"))
    dealt = rows.join(mixed, "key").join(brief, "node").withColumn("blk", F.pmod(F.xxhash64("node"), "blocks").cast("int"))
    dealt = dealt.withColumn("o", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("key", F.least("blk", "o").alias("p"), F.greatest("blk", "o").alias("q"), "comp", "blk", "n", "node", "pos", "brief")
    return dealt.repartition("key", "p", "q").sortWithinPartitions("key", "p", "q", "comp", "node")


def _common(plain: DataFrame, width: int, rows: int) -> tuple[np.ndarray, np.ndarray]:
    """The shingles that most texts of a sample have, sorted, and in how many of them."""
    share = max(1, -(-rows // SAMPLE))
    some = plain.where(F.pmod(F.xxhash64("doc_id"), F.lit(share)) == 0).mapInArrow(lean(_shingles(width)), "node long, s array<long>")
    counted = some.select(F.explode("s").alias("s")).groupBy("s").agg(F.count(F.lit(1)).alias("c")).where("c > 1")
    top = sorted((r.s, r.c) for r in counted.orderBy(F.desc("c"), "s").limit(COMMON).collect())
    return np.array([s for s, _ in top], dtype=np.int64), np.array([c for _, c in top], dtype=np.int64)


def _verified(plain: DataFrame, bits: DataFrame, met: DataFrame, similarity: float, width: int, work: Workspace, name: str, rows: int) -> DataFrame:
    """u, v: the pairs of ``met`` whose sets of shingles are as similar as asked."""
    sides = [bits.select(F.col("node").alias(x), F.col("n").alias(f"n_{x}"), F.col("bits").alias(f"bits_{x}")) for x in "ab"]
    near = met.join(sides[0], "a").join(sides[1], "b").select("a", "b", "n_a", "n_b", "bits_a", "bits_b").mapInArrow(lean(_close(similarity)), "a long, b long")
    met = work.put(near, f"close-{name}", rows, each=2_500)
    wanted = met.select(F.col("a").alias("node")).union(met.select("b")).distinct()
    wanted = work.put(wanted, f"wanted-{name}", rows)
    # where the ids can be broadcast, no other text is shuffled
    few = row_count(wanted) <= LISTED
    sets = plain.join(F.broadcast(wanted) if few else wanted, F.col("doc_id") == F.col("node"), "left_semi").dropDuplicates(["doc_id", "text"]).select(F.col("doc_id").alias("node"), "text")
    sets = work.put(sets.mapInArrow(lean(_shingles(width)), "node long, s array<long>").withColumn("n", F.size("s")), f"sets-{name}")
    a, b = (sets.select(F.col("node").alias(x), F.col("s").alias(f"s_{x}"), F.col("n").alias(f"n_{x}")) for x in "ab")
    both = met.join(a, "a").join(b, "b")
    common = F.size(F.array_intersect("s_a", "s_b"))
    links = both.where(common >= F.lit(similarity) * (F.col("n_a") + F.col("n_b") - common)).select(F.col("a").alias("u"), F.col("b").alias("v"))
    links = work.put(links.distinct(), f"links-{name}", rows)
    work.drop(f"sets-{name}")
    return links
