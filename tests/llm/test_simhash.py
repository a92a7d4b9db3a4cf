"""Fingerprints, block tables and near-duplicate groups against plain Python."""

import hashlib
import math
import re

import pytest
import xxhash
from pyspark.sql import functions as F

from ucqlearn.llm import queries
from ucqlearn.llm.components import components
from ucqlearn.llm.common import Workspace
from ucqlearn.llm.neardup import near_duplicates, variant_groups
from ucqlearn.llm.simhash import fingerprint_report, fingerprints, within_radius

SF = "/root/testdata/sf0.01"
LOWER = {i: i + 32 for i in range(65, 91)}


def plain_print(text, width):
    words = [w for w in re.split(r"[\x20\x09-\x0D]+", (text or "").translate(LOWER)) if w]
    terms = [" ".join(words[i : i + width]) for i in range(max(len(words) - width, 0) + 1)] if words else []
    hashes = [xxhash.xxh64_intdigest(t.encode(), seed=42) for t in terms]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes)) if hashes else 0


def groups(prints, radius):
    ids, up = sorted(prints), {i: i for i in prints}

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for x, a in enumerate(ids):
        for b in ids[x + 1 :]:
            if (prints[a] ^ prints[b]).bit_count() <= radius:
                ra, rb = root(a), root(b)
                up[max(ra, rb)] = min(ra, rb)
    return {i: root(i) for i in ids}


def test_op10_whole_table(spark):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect()}
    prints = {i: plain_print(t, 3) for i, t in docs.items()}
    want = {(i, f"{prints[i]:016x}", c) for i, c in groups(prints, 3).items()}
    assert {tuple(r) for r in queries.op10_simhash_neardup(spark, SF).collect()} == want


ODD = [(0, None), (1, ""), (2, " \n\t "), (3, "One"), (4, "one"), (5, "a b"), (6, "É été a b c d"), (7, "w " * 70000), (8, "a\x0bb\x0cc d e f"), (None, "a b c d"), (None, None), (9, "x y z q"), (9, "x y z q")]


@pytest.mark.parametrize("width", [1, 3, 5])
def test_fingerprints_of_odd_texts(spark, width):
    df = spark.createDataFrame([(i, t, 7) for i, (_, t) in enumerate(ODD)], "k int, text string, fp int")
    got = {r.k: r.fp % (1 << 64) for r in fingerprints(df, ["k"], "text", width).collect()}
    assert got == {i: plain_print(t, width) for i, (_, t) in enumerate(ODD)}


def test_neardup_edge_cases(spark):
    df = spark.createDataFrame([(i, t, 1, 2) for i, t in ODD], "doc_id long, text string, component_id int, fp int")
    got = {r.doc_id: r.component_id for r in near_duplicates(spark, df).collect()}
    assert got[None] is None and got[0] == got[1] == got[2] == 0 and got[3] == got[4] == 3 and got[9] == 9
    assert near_duplicates(spark, df.where("false")).count() == 0


def test_links_by_both_indexes(spark):
    import random

    rng = random.Random(5)
    seeds = [rng.getrandbits(64) for _ in range(20)]
    values = set(seeds) | {0, (1 << 64) - 1}
    for s in seeds:
        for _ in range(8):
            x = s
            for b in rng.sample(range(64), rng.randint(1, 5)):
                x ^= 1 << b
            values.add(x)
    signed = [v - (1 << 64) if v >> 63 else v for v in values]
    df = spark.createDataFrame([(v,) for v in signed], "fp long")
    pairs = lambda r: sorted((a, b) for a in signed for b in signed if a < b and ((a ^ b) % (1 << 64)).bit_count() <= r)
    for r in (1, 3, 5):
        want = groups({v % (1 << 64): v % (1 << 64) for v in signed}, r)
        sets = lambda named: sorted(sorted(k for k in named if named[k] == g) for g in set(named.values()))
        got = {x.node % (1 << 64): x.component for x in variant_groups(df, Workspace(spark, "t"), None, r).collect()}
        assert sets(got) == [x for x in sets(want) if len(x) > 1]
    for r, blocks in ((2, 4), (3, 5), (3, 4)):
        assert sorted(tuple(x)[:2] for x in within_radius(df, r, blocks).collect()) == pairs(r)


def test_dense_groups_link_without_their_pairs(spark):
    """Two families that share keys: all within 3 bits of their own centre, the centres 5 bits apart; and a chain."""
    far = sum(1 << b for b in (3, 9, 40, 50, 60))
    values = {c ^ 1 << i ^ (1 << j if j != i else 0) for c in (0, far) for i in range(64) for j in range(i, 64, 7)}
    chain = [(1 << 64) - 1]
    for k in range(20):
        chain.append(chain[-1] ^ (7 << 3 * k))
    named = {v: v for v in values | set(chain)}
    want = groups(named, 3)
    rows = [(v - (1 << 64) if v >> 63 else v,) for v in named]
    got = {x.node % (1 << 64): x.component for x in variant_groups(spark.createDataFrame(rows, "fp long"), Workspace(spark, "t")).collect()}
    sets = lambda n: sorted(sorted(k for k in n if n[k] == g) for g in set(n.values()))
    assert sets(got) == [x for x in sets(want) if len(x) > 1]


def test_repeated_rows_vote_apart(spark):
    """Votes of very many equal rows don't run over."""
    text = "w " * 8194
    df = spark.createDataFrame([(1, text)] * 300 + [(None, text)] * 3 + [(2, text + "x")], "doc_id long, text string")
    rows = near_duplicates(spark, df).collect()
    assert len(rows) == 304 and {r.fp % (1 << 64) for r in rows} <= {plain_print(text, 3), plain_print(text + "x", 3)}
    assert {(r.doc_id, r.component_id) for r in rows} == {(1, 1), (2, 1), (None, None)}


def test_components_chain_and_star(spark):
    links = [(i, i + 1) for i in range(40)] + [(100, i) for i in range(101, 140)] + [(200, 200)] + [(7, 3)] * 3
    got = {r.node: r.component for r in components(spark.createDataFrame(links, "u long, v long"), Workspace(spark, "t")).collect()}
    assert got == {i: 0 for i in range(41)} | {i: 100 for i in range(100, 140)}


def test_op9_whole_table(spark):
    docs = {r.doc_id: r.text or "" for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect()}
    ids = sorted(docs, reverse=True)
    prints = {i: plain_print(t, 5) for i, t in docs.items()}
    near = lambda a, b: max(0.0, math.cos((a ^ b).bit_count() * math.pi / 64))
    rows = {r.doc_id: r for r in queries.op9_document_fingerprints(spark, SF).collect()}
    assert len(rows) == len(docs)
    for at, i in enumerate(ids):
        j = ids[(at + 1) % len(ids)]
        t = docs[i]
        third = len(t) // 3
        edited = t[: len(t) - third] + docs[j][:third]
        r = rows[i]
        assert (r.n_chars, r.edited_sha256) == (len(t), hashlib.sha256(edited.encode()).hexdigest())
        assert r.fingerprint == f"{prints[i]:016x}" and r.edited_fingerprint == f"{plain_print(edited, 5):016x}"
        assert abs(r.near_edited - near(prints[i], plain_print(edited, 5))) < 1e-9 and abs(r.near_next - near(prints[i], prints[j])) < 1e-9
        if at % 50 == 0:
            assert r.n_near == sum((prints[i] ^ p).bit_count() <= 3 for p in prints.values()) - 1
    good = sum(r.near_edited > r.near_next for r in rows.values())
    assert good > 0.9 * len(rows)


def test_op9_edge_cases(spark):
    df = spark.createDataFrame([(i, t, 1) for i, t in ODD], "doc_id long, text string, fp int")
    rows = {r.doc_id: r for r in fingerprint_report(spark, df).collect()}
    assert set(rows) == set(range(10)) and rows[0].edited_sha256 == hashlib.sha256(b"").hexdigest()
    assert rows[0].fingerprint == rows[1].fingerprint == "0" * 16
    assert fingerprint_report(spark, df.where("false")).count() == 0
    sole = fingerprint_report(spark, df.where("doc_id = 6")).first()
    assert sole.edited_sha256 == hashlib.sha256("É été a bÉ ét".encode()[:0] + ("É été a b c d"[: 13 - 4] + "É été a b c d"[:4]).encode()).hexdigest()


def test_few_links_take_one_task_and_no_rounds(spark):
    import os
    import random

    r = random.Random(5)
    links = [(r.randrange(-300, 300), r.randrange(-300, 300)) for _ in range(250)] + [(7, 7), (900, 901), (901, 900)]
    df = spark.createDataFrame(links, "u long, v long")
    work = Workspace(spark, "few")
    got = {x.node: x.component for x in components(df, work).collect()}
    assert got == {x.node: x.component for x in components(df, work, name="rounds", few=0).collect()}
    folder = work.root.removeprefix("file://")
    assert sorted(n for n in os.listdir(folder) if n.startswith("stars")) == ["stars-0", "stars-found"]
    assert not [n for _, _, names in os.walk(folder) for n in names if "_SUCCESS" in n]
    assert components(df.limit(0), work, name="none").count() == 0
