"""SimHash near-dedup over a Gray-ordered hierarchical Hamming index.

Fingerprints: 64 bits, one majority vote per bit over XXH64 of the word
shingles of a whole text.  Rows with equal fingerprints form one class, so a
group of copies costs one index entry whatever its size.  Distinct
fingerprints are range-partitioned by Gray rank into blocks.  The index is one
hierarchy over that order: fingerprints, groups of FAN consecutive ones, groups
of groups up to a block, blocks, groups of WIDE blocks up to the root.  A node
holds the bits that all its members share, mask and pattern.

The index joins itself from the root down: two nodes meet only if their
parents did, and part for good, with all that lies below them, once the
differences in the bits that both share pass the limit.  Above the blocks,
node pairs are rows and a level is an equi-join on the parent; below, a task
takes a block and a bounded number of the blocks that it meets, and goes on in
arrays.  Two nodes whose unshared bits cannot pass the limit either are joined
whole.  Tasks return spanning edges, never pairs of copies.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from arcfield.deploy import save, ship
from arcfield.operators.components import components

BITS, LIMIT = 64, 3
#: Fingerprints of a block; children of a node inside a block and above; blocks a task compares its own with.
BLOCK, FAN, WIDE, PARTNERS = 1 << 14, 2, 16, 16


def gray_rank(x: np.ndarray) -> np.ndarray:
    """Place of each 64-bit word in the reflected Gray sequence."""
    x = x.astype(np.uint64)
    for s in (1, 2, 4, 8, 16, 32):
        x = x ^ (x >> np.uint64(s))
    return x


def fingerprint(text: bytes | None, width: int) -> int:
    """Signed 64-bit SimHash of one UTF-8 text (A-Z lower-cased); 0 where it has no words."""
    from xxhash import xxh64_digest

    words = (text or b"").lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    if len(words) <= width:
        digests = xxh64_digest(joined, 42)
    else:
        ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
        starts = np.concatenate(([0], ends[:-1] + 1))
        digests = b"".join([xxh64_digest(joined[s:e], 42) for s, e in zip(starts[: 1 - width].tolist(), ends[width - 1 :].tolist())])
    n = len(digests) // 8
    votes = np.zeros(BITS, np.int64)
    for at in range(0, len(digests), 1 << 19):
        part = np.frombuffer(digests[at : at + (1 << 19)], np.uint8).reshape(-1, 8)
        votes += np.unpackbits(part, axis=1).sum(axis=0, dtype=np.int32)
    return int.from_bytes(np.packbits(votes * 2 > n).tobytes(), "big", signed=True)


def fingerprints(docs: DataFrame, text: str = "text", width: int = 3, out: str = "fp") -> DataFrame:
    """``docs`` with a signed 64-bit column ``out``; ``text`` itself is not carried."""
    ship(docs.sparkSession)

    @F.pandas_udf("long")
    def sign(texts: pd.Series) -> pd.Series:
        return pd.Series([fingerprint(t, width) for t in texts], dtype="int64")

    return docs.withColumn(out, sign(F.col(text).cast("binary"))).drop(text)


def _fold(label: np.ndarray, u: np.ndarray, v: np.ndarray) -> None:
    """Merge the components of ``label`` (in place; labels are the smallest member) along the edges (u, v)."""
    while len(u):
        a, b = label[u], label[v]
        differ = a != b
        if not differ.any():
            return
        u, v, a, b = u[differ], v[differ], a[differ], b[differ]
        np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
        while True:
            up = label[label]
            if np.array_equal(up, label):
                break
            label[:] = up


def _levels(fp: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
    """Levels from single fingerprints to the root of (shared-bit mask, pattern) over Gray-ordered ``fp``."""
    both = some = fp
    levels = [(np.full(len(fp), ~np.uint64(0)), fp)]
    while len(both) > 1:
        cuts = np.arange(0, len(both), FAN)
        both, some = np.bitwise_and.reduceat(both, cuts), np.bitwise_or.reduceat(some, cuts)
        levels.append((~(both ^ some), both))
    return levels


def _range(nodes: np.ndarray, span: int, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Members below each node, node after node, and their number for each."""
    first = nodes * span
    n = np.minimum(size, first + span) - first
    return np.repeat(first - (np.cumsum(n) - n), n) + np.arange(n.sum()), n


def gray_join(left: np.ndarray, right: np.ndarray, limit: int) -> tuple[np.ndarray, np.ndarray, dict]:
    """Spanning edges (u, v) of the links within ``limit`` bits between two Gray-ordered arrays, and counts.

    The counts are node pairs that met (``met``), that their shared bits parted
    (``parted``) and that were joined whole (``whole``), above single
    fingerprints, and the pairs of fingerprints compared (``compared``).
    """
    n = len(left)
    label = np.arange(n + len(right))
    counts = {"met": 0, "parted": 0, "whole": 0, "compared": 0}
    if not n or not len(right):
        return left[:0], left[:0], counts
    trees = [_levels(left), _levels(right)]
    for t in trees:
        t += [t[-1]] * (max(map(len, trees)) - len(t))
    stack = [(len(trees[0]) - 1, np.zeros(1, np.int64), np.zeros(1, np.int64))]
    held, waiting = [], 0
    k = np.arange(FAN)
    while stack:
        depth, a, b = stack.pop()
        if len(a) > 1 << 16:
            half = len(a) // 2
            stack += [(depth, a[:half], b[:half]), (depth, a[half:], b[half:])]
            continue
        (ma, pa), (mb, pb) = (t[depth] for t in trees)
        shared = ma[a] & mb[b]
        apart = np.bitwise_count((pa[a] ^ pb[b]) & shared)
        near = apart <= limit
        counts["met" if depth else "compared"] += len(a)
        if depth:
            counts["parted"] += len(a) - int(near.sum())
        a, b, shared, apart = a[near], b[near], shared[near], apart[near]
        if depth:
            # differences so far and every bit that may still differ
            whole = apart + np.bitwise_count(~shared) <= limit
            counts["whole"] += int(whole.sum())
        else:
            whole = np.ones(len(a), bool)
        if whole.any():
            x, nx = _range(a[whole], FAN**depth, n)
            y, ny = _range(b[whole], FAN**depth, len(right))
            first = a[whole] * FAN**depth
            held += [(np.repeat(first, nx), x), (np.repeat(first, ny), y + n)]
            waiting += len(x) + len(y)
            if waiting > 1 << 20:
                _fold(label, *(np.concatenate(c) for c in zip(*held)))
                held, waiting = [], 0
        a, b = a[~whole], b[~whole]
        if len(a):
            x = (a[:, None, None] * FAN + k[None, :, None] + 0 * k[None, None, :]).ravel()
            y = (b[:, None, None] * FAN + k[None, None, :] + 0 * k[None, :, None]).ravel()
            ok = (x < len(trees[0][depth - 1][0])) & (y < len(trees[1][depth - 1][0]))
            stack.append((depth - 1, x[ok], y[ok]))
    if held:
        _fold(label, *(np.concatenate(c) for c in zip(*held)))
    every = np.concatenate((left, right))
    u, v = every, every[label]
    return u[u != v], v[u != v], counts


def _cut(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Blocks of one range of Gray ranks: place, bits set in all and in any member, members."""
    from pyspark import TaskContext

    fp = [p["fp"].to_numpy(np.int64) for p in parts]
    fp = np.concatenate(fp).view(np.uint64) if fp else np.zeros(0, np.uint64)
    if not len(fp):
        return
    blocks = np.array_split(fp, max(1, round(len(fp) / BLOCK)))
    both, some = ([f(b).view(np.int64) for b in blocks] for f in (np.bitwise_and.reduce, np.bitwise_or.reduce))
    yield pd.DataFrame({"part": TaskContext.get().partitionId(), "seq": range(len(blocks)), "both": both, "some": some, "fps": [b.tobytes() for b in blocks]})


def gray_blocks(classes: DataFrame) -> DataFrame:
    """(node, both, some, fps): the distinct column ``fp`` in Gray order, cut into blocks; nodes ascend with rank."""
    spark = classes.sparkSession
    g = F.col("fp")
    for s in (1, 2, 4, 8, 16, 32):
        g = g.bitwiseXOR(F.shiftrightunsigned(g, s))
    # ranks are unsigned
    ranked = classes.select("fp", g.bitwiseXOR(F.lit(-(1 << 63))).alias("g"))
    n = classes.count()
    parts = max(1, -(-n // (BLOCK << 6)), min(-(-n // BLOCK), int(spark.conf.get("spark.sql.shuffle.partitions"))))
    ranged = ranked.repartitionByRange(parts, "g").sortWithinPartitions("g").select("fp")
    blocks = save(ranged.mapInPandas(_cut, "part int, seq int, both long, some long, fps binary"), "gray-blocks")
    most = int(blocks.agg(F.max("seq")).first()[0] or 0) + 1
    return blocks.select((F.col("part").cast("long") * most + F.col("seq")).alias("node"), "both", "some", "fps")


def meeting_blocks(blocks: DataFrame, limit: int) -> DataFrame:
    """(a, b), a <= b: blocks that no node above them parts, level by level from the root."""
    level = blocks.select("node", "both", "some")
    levels, top = [level], int(level.agg(F.max("node")).first()[0] or 0)
    while top:
        level = level.groupBy(F.floor(F.col("node") / WIDE).alias("node")).agg(F.bit_and("both").alias("both"), F.bit_or("some").alias("some"))
        levels.append(level)
        top //= WIDE
    met = levels[-1].select(F.col("node").alias("a"), F.col("node").alias("b"))
    for level in reversed(levels[:-1]):
        a, b = (level.select(F.floor(F.col("node") / WIDE).alias(f"up_{k}"), F.col("node").alias(f"{k}_"), F.col("both").alias(f"{k}_both"), F.col("some").alias(f"{k}_some")) for k in "ab")
        shared = F.bitwise_not(F.col("a_both").bitwiseXOR(F.col("a_some")).bitwiseOR(F.col("b_both").bitwiseXOR(F.col("b_some"))))
        apart = F.bit_count(F.col("a_both").bitwiseXOR(F.col("b_both")).bitwiseAND(shared))
        met = met.join(a, met.a == F.col("up_a")).join(b, met.b == F.col("up_b")).where((F.col("a_") <= F.col("b_")) & (apart <= limit))
        met = met.select(F.col("a_").alias("a"), F.col("b_").alias("b"))
    return met


def near_links(classes: DataFrame, limit: int = LIMIT) -> DataFrame:
    """(a, b): spanning edges of all links within ``limit`` bits among the distinct column ``fp``."""
    spark = classes.sparkSession
    ship(spark)
    blocks = gray_blocks(classes)
    met = save(meeting_blocks(blocks, limit), "gray-meetings")
    # either block may take the other; turns even out what each has to do
    turn = (F.col("a") + F.col("b")) % 2 == 0
    met = met.select(F.when(turn, F.col("a")).otherwise(F.col("b")).alias("own"), F.when(turn, F.col("b")).otherwise(F.col("a")).alias("node"))
    met = met.withColumn("chunk", F.floor(F.col("node") / PARTNERS))
    mine = met.select("own", "chunk").distinct().select("own", "chunk", F.lit(True).alias("is_own"), F.col("own").alias("node"))
    asked = mine.unionByName(met.select("own", "chunk", F.lit(False).alias("is_own"), "node")).join(blocks.select("node", "fps"), "node")
    n = max(int(spark.conf.get("spark.sql.shuffle.partitions")), met.count() * BLOCK * 8 >> 26)

    def meet(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("node")
        own = np.frombuffer(pdf.loc[pdf["is_own"], "fps"].iloc[0], np.uint64)
        others = np.frombuffer(b"".join(pdf.loc[~pdf["is_own"], "fps"]), np.uint64)
        u, v, _ = gray_join(own, others, limit)
        return pd.DataFrame({"a": u.view(np.int64), "b": v.view(np.int64)})

    return asked.repartition(n, "own", "chunk").groupBy("own", "chunk").applyInPandas(meet, "a long, b long").distinct()


def simhash_components(docs: DataFrame, id_col: str = "doc_id", text: str = "text", width: int = 3, limit: int = LIMIT) -> DataFrame:
    """(id, fp, component_id): SimHash of each row and the smallest id reachable over links of ``limit`` bits.

    Null and empty texts have fingerprint zero and link like any other; texts
    shorter than a shingle vote with their whole word sequence.  A repeated row
    gives a row each.  A null id gets a class as well but is never a
    component's name while the component holds another id.  Other columns of
    ``docs`` are not read.  An empty table gives an empty result.
    """
    rows = save(fingerprints(docs.select(F.col(id_col).alias("id"), F.col(text).alias("text")), width=width), "fingerprints")
    classes = save(rows.groupBy("fp").agg(F.min("id").alias("first_id")), "classes")
    tied = components(near_links(classes, limit), "a", "b")
    roots = classes.join(tied, classes.fp == tied.node, "left").select("fp", "first_id", F.coalesce("root", "fp").alias("root"))
    names = roots.groupBy("root").agg(F.min("first_id").alias("component_id"))
    named = save(roots.join(names, "root").select("fp", "component_id"), "named")
    return rows.join(named, "fp").select(F.col("id").alias(id_col), "fp", "component_id")


def digest(docs: DataFrame) -> DataFrame:
    return simhash_components(docs).select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, width: int = 3) -> DataFrame:
    """``docs`` (with column doc_id) less all but the smallest id of each near-duplicate group.

    Rows that share that id stay all; so does a row without an id.  Null and
    empty texts are copies of each other.  An empty table stays empty.
    """
    found = simhash_components(docs, width=width)
    gone = found.where("doc_id > component_id").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)
