"""SimHash fingerprints by DataFrame functions only, permuted block tables, and the edited-text comparison.

A term is a run of ``width`` words; its weight is the number of times it occurs. Every term's 64-bit hash votes
on each bit, and a bit is set when more than half the weight has it set. The votes are counted three bits to a
long, so that the hot aggregate keeps 22 sums and not 64.
"""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Workspace, ascii_lower, few_files, row_count, space_words

LANE = 21
LANE_MASK = 1 | 1 << LANE | 1 << 2 * LANE
CHUNK = 8192  # terms counted in one packed sum; a lane holds 2**21
BITS = 64


def _unsigned_hex(x: Column) -> Column:
    return F.lower(F.lpad(F.hex(x), 16, "0"))


def fingerprints(df: DataFrame, keys: list[str], text: str, width: int, lower: bool = True) -> DataFrame:
    """One row for each distinct ``keys``: keys, ``fp`` (long), ``n_terms`` (long).

    Null, empty and blank texts have fingerprint 0 and no terms; a text of fewer than ``width`` words has one
    term, its whole word sequence. ``keys`` must be unique in ``df``, as the votes of a key are added. Texts of any length are counted in chunks, none is cut.
    """
    raw = F.coalesce(F.col(text), F.lit(""))
    words = df.select(*keys, space_words(ascii_lower(raw) if lower else raw).alias("_w"))
    n = F.size("_w")
    last = F.when(n > 0, F.greatest(n - width, F.lit(0)))
    terms = words.select(*keys, "_w", F.explode_outer(F.when(n > 0, F.sequence(F.lit(0), last))).alias("_i"))
    term = F.concat_ws(" ", *[F.get("_w", F.col("_i") + k) for k in range(width)])
    hashed = terms.select(*keys, F.floor(F.col("_i") / CHUNK).alias("_c"), F.when(F.col("_i").isNotNull(), F.xxhash64(term)).alias("_h"))
    packed = [F.sum(F.shiftrightunsigned("_h", k).bitwiseAND(F.lit(LANE_MASK))).alias(f"_p{k}") for k in range(LANE)]
    packed.append(F.sum(F.shiftrightunsigned("_h", 63)).alias("_p21"))
    counts = hashed.groupBy(*keys, "_c").agg(*packed, F.count("_h").alias("_n"))

    def ones(bit: int) -> Column:
        if bit == 63:
            return F.sum("_p21")
        return F.sum(F.shiftrightunsigned(f"_p{bit % LANE}", LANE * (bit // LANE)).bitwiseAND(F.lit((1 << LANE) - 1)))

    votes = counts.groupBy(*keys).agg(F.sum("_n").alias("n_terms"), *[ones(b).alias(f"_b{b}") for b in range(BITS)])
    fp = F.lit(0).cast("long")
    for b in range(BITS):
        value = 1 << b if b < 63 else -(1 << 63)
        fp = fp.bitwiseOR(F.when(F.col(f"_b{b}") * 2 > F.col("n_terms"), F.lit(value)).otherwise(F.lit(0)).cast("long"))
    return votes.select(*keys, fp.alias("fp"), "n_terms")


def hamming(a: Column, b: Column) -> Column:
    return F.bit_count(a.bitwiseXOR(b))


def likeness(a: Column, b: Column) -> Column:
    """Cosine of the angle that the share of differing bits stands for: 1 equal, 0 unrelated or opposed."""
    return F.greatest(F.lit(0.0), F.cos(hamming(a, b) * F.lit(3.141592653589793 / BITS)))


def block_keys(fp: Column, radius: int, blocks: int) -> Column:
    """Array of table keys. With ``blocks`` blocks, two fingerprints within ``radius`` agree on at least
    blocks - radius of them; each choice of that many blocks is one permuted table, its blocks moved to the front."""
    edges = [round(i * BITS / blocks) for i in range(blocks + 1)]
    keys = []
    for number, chosen in enumerate(combinations(range(blocks), blocks - radius)):
        mask = sum(((1 << edges[b + 1]) - (1 << edges[b])) for b in chosen)
        signed = mask - (1 << 64) if mask >> 63 else mask
        keys.append(F.struct(F.lit(number).alias("t"), fp.bitwiseAND(F.lit(signed)).alias("k")))
    return F.array(*keys)


def within_radius(classes: DataFrame, radius: int = 3, blocks: int = 5) -> DataFrame:
    """All pairs of different fingerprints in ``classes`` (column fp, each once) at most ``radius`` bits apart:
    a, b (a < b), distance, and other columns of ``classes`` with _a and _b. Each pair comes once: from the first table in which it agrees."""
    if not 0 < radius < blocks:
        raise ValueError("radius must be over 0 and under the number of blocks")
    more = [c for c in classes.columns if c != "fp"]
    entries = classes.select(*classes.columns, F.explode(block_keys(F.col("fp"), radius, blocks)).alias("e")).select(*classes.columns, "e.t", "e.k")
    left, right = (entries.withColumnsRenamed({"fp": x} | {c: f"{c}_{x}" for c in more}) for x in "ab")
    edges = [round(i * BITS / blocks) for i in range(blocks + 1)]
    x = F.col("a").bitwiseXOR(F.col("b"))
    masks = [sum(((1 << edges[b + 1]) - (1 << edges[b])) for b in chosen) for chosen in combinations(range(blocks), blocks - radius)]
    first = F.coalesce(*[F.when(x.bitwiseAND(F.lit(m - (1 << 64) if m >> 63 else m)) == 0, F.lit(i)) for i, m in enumerate(masks)])
    pairs = left.join(right, (left.t == right.t) & (left.k == right.k) & (F.col("a") < F.col("b")) & (F.bit_count(x) <= radius) & (first == left.t))
    return pairs.select("a", "b", F.bit_count(x).alias("distance"), *[f"{c}_{x}" for c in more for x in "ab"])


def successors(df: DataFrame, key: str, work: Workspace, rows: int, each: int = 500_000) -> DataFrame:
    """key, next_key for each distinct key: the next in descending order; after the last comes the first.

    The keys are dealt into ranges of about ``each`` keys, which are written, ordered range by range, and tied together at their
    ends from one row a range. No task orders all keys.
    """
    keys = df.select(F.col(key).alias("k")).where(F.col(key).isNotNull()).distinct()
    sliced = work.put(keys.repartitionByRange(max(1, -(-rows // each)), "k").select("k", F.spark_partition_id().alias("s")), f"ranges-{key}")
    ends = sliced.groupBy("s").agg(F.max("k").alias("top"))
    from pyspark.sql import Window

    below = Window.partitionBy(F.lit(0)).orderBy(F.col("s"))
    everyone = Window.partitionBy(F.lit(0))
    ties = ends.select("s", F.coalesce(F.lag("top").over(below), F.max("top").over(everyone)).alias("after"))
    inside = Window.partitionBy("s").orderBy(F.col("k").desc())
    chained = sliced.select("s", "k", F.lead("k").over(inside).alias("n"))
    return chained.join(F.broadcast(ties), "s").select(F.col("k").alias(key), F.coalesce("n", "after").alias("next_key"))


def edited_texts(df: DataFrame, work: Workspace, rows: int) -> DataFrame:
    """doc_id, text, edited, next_id: the last third of the code points gives way to as many first ones of the
    next document in descending doc_id. Rows need unique, non-null doc_id; a sole document follows itself."""
    docs = df.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    order = successors(docs, "doc_id", work, rows)
    sized = docs.select("doc_id", F.char_length("text").alias("n"))
    wanted = order.join(sized, "doc_id").select("doc_id", F.col("next_key").alias("next_id"), F.floor(F.col("n") / 3).cast("int").alias("third"))
    heads = docs.join(wanted.select(F.col("doc_id").alias("for_id"), F.col("next_id").alias("doc_id"), "third"), "doc_id")
    grafts = heads.select(F.col("for_id").alias("doc_id"), F.col("doc_id").alias("next_id"), "third", F.substring("text", F.lit(1), F.col("third")).alias("graft"))
    kept = F.substring("text", F.lit(1), F.char_length("text") - F.col("third"))
    return docs.join(grafts, "doc_id").select("doc_id", "text", F.concat(kept, "graft").alias("edited"), "next_id")


def fingerprint_report(spark, docs: DataFrame, width: int = 5, radius: int = 3, blocks: int = 5) -> DataFrame:
    """Fingerprints of all documents and of their edited texts, likeness to both neighbours, and the number of
    other documents within ``radius`` bits (``n_near``, found through the block tables over distinct fingerprints).

    Null text counts as empty. Rows without doc_id are left out, as they have no place in the order; of rows
    with one doc_id the smallest text is used. An empty table gives an empty result. Other columns are ignored.
    """
    work = Workspace(spark, "simhash")
    rows = row_count(docs)
    facts = ["doc_id", "next_id", "n_chars", "edited_sha256"]
    both = edited_texts(_one_text(docs), work, rows).select("doc_id", "next_id", F.char_length("text").cast("long").alias("n_chars"), F.sha2(F.encode("edited", "UTF-8"), 256).alias("edited_sha256"), F.explode(F.map_from_arrays(F.array(F.lit(0), F.lit(1)), F.array("text", "edited"))).alias("v", "t"))
    votes = fingerprints(both, [*facts, "v"], "t", width)
    pick = lambda v: F.max(F.when(F.col("v") == v, F.col("fp")))
    prints = work.put(votes.groupBy(*facts).agg(pick(0).alias("fp"), pick(1).alias("fp_edited")), "prints", rows, exchange=True)
    classes = prints.groupBy("fp").agg(F.count(F.lit(1)).alias("size"))
    # the number of documents behind a fingerprint travels with it, and pairs are summed where they are found
    pairs = within_radius(classes, radius, blocks)
    sides = pairs.select(F.explode(F.array(F.struct(F.col("a").alias("fp"), F.col("size_b").alias("n")), F.struct(F.col("b").alias("fp"), F.col("size_a").alias("n")))).alias("e"))
    others = sides.groupBy(F.col("e.fp").alias("fp")).agg(F.sum("e.n").alias("others"))
    near = classes.join(others, "fp", "left").select("fp", (F.col("size") - 1 + F.coalesce("others", F.lit(0))).alias("n_near"))
    joined = prints.join(prints.select(F.col("doc_id").alias("next_id"), F.col("fp").alias("fp_next")), "next_id").join(near, "fp")
    report = joined.select(
        "doc_id",
        "n_chars",
        "edited_sha256",
        _unsigned_hex(F.col("fp")).alias("fingerprint"),
        _unsigned_hex(F.col("fp_edited")).alias("edited_fingerprint"),
        likeness(F.col("fp"), F.col("fp_edited")).alias("near_edited"),
        likeness(F.col("fp"), F.col("fp_next")).alias("near_next"),
        "n_near",
    )
    return few_files(report, rows)


def _one_text(docs: DataFrame) -> DataFrame:
    """doc_id and text. Rows without doc_id go; of rows that share one, the smallest text stays. The narrow check
    of the ids comes first, so that texts are only aggregated where an id does repeat."""
    rows = docs.select("doc_id", "text").where(F.col("doc_id").isNotNull())
    repeated = rows.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").limit(1).count()
    return rows.groupBy("doc_id").agg(F.min("text").alias("text")) if repeated else rows
