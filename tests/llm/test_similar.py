"""Groups by shingle overlap against brute force."""

import random

import numpy as np

from ucqlearn.llm.similar import _apart, parities, similar_groups

SF = "/root/testdata/sf0.01"


def shingles(text, width=5):
    w = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "").encode().split()
    return {tuple(w[i : i + width]) for i in range(max(len(w) - width, 0) + 1)}


def brute(docs, similarity=0.8):
    sets, up = {i: shingles(t) for i, t in docs}, {i: i for i, _ in docs}
    by, pairs = {}, set()
    for i, s in sets.items():
        for x in s:
            by.setdefault(x, []).append(i)

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for some in by.values():
        pairs |= {(a, b) for a in some for b in some if a < b}
    linked = {(a, b) for a, b in pairs if len(sets[a] & sets[b]) >= similarity * len(sets[a] | sets[b])}
    for a, b in linked:
        x, y = root(a), root(b)
        up[max(x, y)] = min(x, y)
    return {i: root(i) for i in up}, linked


def test_planted_copies(spark):
    rng = random.Random(8)
    vocabulary = ["".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 7))) for _ in range(900)]
    docs, base = [], []
    for i in range(60):
        base.append([rng.choice(vocabulary) for _ in range(rng.randint(80, 400))])
        docs.append((i, " ".join(base[-1])))
    for i in range(60, 360):
        w = list(base[i % 60])
        for _ in range(rng.randint(0, max(1, len(w) // 80))):
            w[rng.randrange(len(w))] = rng.choice(vocabulary)
        docs.append((i, " ".join(w)))
    df = spark.createDataFrame([(i, t, 1) for i, t in docs], "doc_id long, text string, head int")
    got = {r.doc_id: r.component_id for r in similar_groups(spark, df).collect()}
    want, linked = brute(docs)
    assert all(want[i] == want[got[i]] for i in got)  # never joins what brute force keeps apart
    assert sum(got[a] == got[b] for a, b in linked) > 0.97 * len(linked)
    assert len(set(got.values())) <= 1.05 * len(set(want.values()))


def test_whole_table(spark):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect()]
    got = {r.doc_id: r.component_id for r in similar_groups(spark, spark.read.parquet(f"{SF}/documents.parquet")).collect()}
    want, linked = brute(docs)
    print(len(linked), sum(got[a] == got[b] for a, b in linked), len(set(want.values())), len(set(got.values())))
    assert set(got) == set(want) and all(want[i] == want[got[i]] for i in got)
    assert sum(got[a] == got[b] for a, b in linked) > 0.85 * len(linked)


def test_odd_tables(spark):
    odd = [(0, None), (1, ""), (2, " \n"), (3, "One two"), (3, "One two"), (4, "one\ttwo"), (None, "x"), (5, "w " * 30000), (6, "é ü ß")]
    df = spark.createDataFrame([(i, t, 1, 2) for i, t in odd], "doc_id long, text string, node int, a int")
    assert sorted(tuple(r) for r in similar_groups(spark, df).collect()) == [(0, 0), (1, 0), (2, 0), (3, 3), (3, 3), (4, 3), (5, 5), (6, 6)]
    assert similar_groups(spark, df.where("false")).count() == 0


def test_interleaved_families(spark):
    """Families with one word set in different orders, dealt in turn by doc_id: each is found, and none is joined to another."""
    rng = random.Random(5)
    vocabulary = [f"w{i}" for i in range(120)]
    orders = [rng.sample(vocabulary, len(vocabulary)) for _ in range(8)]
    docs = []
    for i in range(240):
        w = list(orders[i % 8])
        at = rng.randrange(len(w) - 1)
        w[at], w[at + 1] = w[at + 1], w[at]
        docs.append((i, " ".join(w)))
    want, linked = brute(docs)
    got = {r.doc_id: r.component_id for r in similar_groups(spark, spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert len(set(want.values())) == 8 and got == want


def test_crossings_against_all_pairs():
    """The last pass leaves no pair out, however its stretches fall into batches and blocks."""
    import numpy as np
    import pyarrow as pa

    from ucqlearn.llm.similar import _crossings

    rng = np.random.default_rng(3)
    rows, want = [], set()
    for key in range(40):
        size = int(rng.integers(2, 40))
        blocks = 1 + key % 3
        own = [(key * 100 + i, int(rng.integers(0, 6)), int(rng.integers(0, blocks)), int(rng.integers(8, 14)), 0) for i in range(size)]
        for node, comp, blk, n, pos in own:
            rows += [(key, min(blk, o), max(blk, o), comp, blk, n, node, pos) for o in range(blocks)]
        want |= {(x[0], y[0]) for x in own for y in own if x[0] < y[0] and x[1] != y[1] and min(x[3], y[3]) >= 0.8 * max(x[3], y[3])}
    rows.sort()
    batches = [pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows[i : i + 17])], names=list("abcdefgh")) for i in range(0, len(rows), 17)]
    got = {(a, b) for out in _crossings(0.8, True)(iter(batches)) for a, b in zip(out.column(0).to_pylist(), out.column(1).to_pylist())}
    assert got == want


def test_cut_and_extended_pairs(spark):
    """Pairs of 0.8 and more in every band: copies cut to a share of their words, and copies with words appended."""
    rng = random.Random(11)
    vocabulary = [f"v{i}" for i in range(3000)]
    docs, kinds = [], {}
    for kind, share in (("cut", 0.83), ("cut", 0.92), ("append", 0.2), ("append", 0.1)):
        for _ in range(40):
            w = [rng.choice(vocabulary) for _ in range(rng.randint(60, 600))]
            other = w[: int(len(w) * share) + 1] if kind == "cut" else w + [rng.choice(vocabulary) for _ in range(int(len(w) * share))]
            kinds[len(docs)] = f"{kind} {share}"
            docs += [(len(docs), " ".join(w)), (len(docs) + 1, " ".join(other))]
    want, linked = brute(docs)
    got = {r.doc_id: r.component_id for r in similar_groups(spark, spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    for kind in sorted(set(kinds.values())):
        ours = [(a, b) for a, b in linked if kinds.get(a) == kind]
        print(kind, len(ours), sum(got[a] == got[b] for a, b in ours))
    assert len(linked) > 100 and got == want


def test_sequences_of_one_polynomial_hash(spark):
    from .test_text_ops import turning

    df = spark.createDataFrame(list(enumerate(turning())), "doc_id long, text string")
    assert sorted(tuple(r) for r in similar_groups(spark, df).collect()) == [(0, 0), (1, 1)]


def test_parities_never_rule_out_a_link():
    rng = np.random.default_rng(3)
    for _ in range(300):
        n = int(rng.integers(1, 900))
        a = np.unique(rng.integers(-(1 << 62), 1 << 62, n))
        b = np.unique(np.concatenate([a[: len(a) - int(rng.integers(0, len(a) // 4 + 1))], rng.integers(-(1 << 62), 1 << 62, int(rng.integers(0, len(a) // 3 + 1)))]))
        apart = len(np.setxor1d(a, b))
        assert _apart(parities(a), parities(b)) <= apart


def test_repeated_ids(spark):
    """A doc_id with two texts has the links of both, and rows that repeat don't hide any."""
    text = lambda k, n=40: " ".join(f"{k}w{i}" for i in range(n))
    rows = [(1, text("a"))] * 30 + [(1, text("b")), (2, text("a", 38)), (3, text("b", 38)), (4, text("c"))]
    got = similar_groups(spark, spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert len(got) == len(rows) and {tuple(r) for r in got} == {(1, 1), (2, 1), (3, 1), (4, 4)}


def test_crossings_make_no_rows_of_texts_that_share_a_shingle_alone():
    import numpy as np
    import pyarrow as pa

    from ucqlearn.llm.similar import BRIEF, SLACK, _crossings, _folded, parities

    r = np.random.default_rng(2)
    draw = lambda n: np.unique(r.integers(-(1 << 62), 1 << 62, n))
    sets = [draw(n) for n in (3, 5, 9, 40, 41, 300, 310, 5000) for _ in range(12)]
    sets += [np.unique(np.concatenate([s[: len(s) - len(s) // 12], draw(len(s) // 12)])) for s in sets]  # likely 0.8 or more
    want = set()
    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            common = len(np.intersect1d(a, b, assume_unique=True))
            if common >= 0.8 * (len(a) + len(b) - common) - SLACK:
                want.add((j, i))
    count = len(sets)
    columns = [np.full(count, 4), np.zeros(count), np.zeros(count), np.arange(count), np.zeros(count), [len(s) for s in sets], np.arange(count), np.zeros(count)]
    names = ["key", "p", "q", "comp", "blk", "n", "node", "pos"]
    batch = pa.RecordBatch.from_arrays([pa.array(np.asarray(c), pa.int64()) if i != 4 else pa.array(np.zeros(count, dtype=np.int32)) for i, c in enumerate(columns)], names=names)
    brief = batch.append_column("brief", pa.array([_folded(parities(s), BRIEF).tobytes() for s in sets], pa.binary()))
    found = lambda batches: {(a, b) for out in _crossings(0.8, True)(iter(batches)) for a, b in zip(out.column(0).to_pylist(), out.column(1).to_pylist())}
    got, plain = found([brief.slice(at, 7) for at in range(0, count, 7)]), found([batch])
    assert len(want) > 60 and want <= got <= plain
    assert len(got) < len(want) + len(plain) // 10
