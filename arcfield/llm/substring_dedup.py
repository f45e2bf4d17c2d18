"""Exact substring dedup over prefix-partitioned suffix trees.

Suffixes are word sequences; a repeat of ``width`` words is an internal node
of that depth or more below which lie suffixes of two documents.  Moving every
suffix would cost many times the text, so three steps narrow them down, each
exact:

1. Anchors.  A window's anchor is the least hash among its runs of RUN words,
   so equal windows have equal anchors, and few distinct anchors cover a text.
   Blocks of documents send their distinct anchors and how many windows each
   has; an anchor of one block alone needs no other block.
2. Subtrees.  Suffixes go to the group of their prefix.  A prefix is the words
   of the anchor, and consecutive suffixes that share it travel as one
   fragment of text.  Where more suffixes than a subtree may hold lie behind
   it, the prefix grows to the whole window.  A block sends one suffix of each
   distinct window, that of its smallest document.  A group sorts its suffixes
   by prefix doubling over word numbers; neighbours that share ``width`` words
   lie below one internal node of that depth, whose smallest document is known.
3. Removal.  Blocks learn which of their suffixes start earlier elsewhere and
   where, add those that start earlier in their own documents, join runs of
   them to maximal repeats, and drop what these cover.

Documents are dealt to blocks once; all three steps read that one exchange.
Windows are compared word by word; hashes only route.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from arcfield.deploy import plan_bytes, ship

WIDTH, RUN = 13, 6
#: Bytes of stored input for one block of documents, one bucket of anchors and one bucket of subtrees; suffixes that one prefix may have.
BLOCK_BYTES, ANCHOR_BYTES, TREE_BYTES, SUBTREE = 4 << 20, 32 << 20, 8 << 20, 1 << 18
_A, _B, _C = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


class _Numbers(dict):
    """A running number for each word."""

    def __missing__(self, word: bytes) -> int:
        self[word] = n = len(self)
        return n


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * _B
    x = (x ^ (x >> np.uint64(27))) * _C
    return x ^ (x >> np.uint64(31))


def _runs(h: np.ndarray, k: int) -> np.ndarray:
    """Hash of every run of ``k`` words; runs go past the end as zeros."""
    out, h = np.zeros(len(h), np.uint64), np.concatenate((h, np.zeros(k, np.uint64)))
    for i in range(k):
        out = out * _A + h[i : i + len(out)]
    return _mix(out)


def _ordered(pdf: pd.DataFrame) -> pd.DataFrame:
    """A block's rows by id and text: exchanges keep no order, and steps refer to windows by number."""
    ids, texts = pdf["id"].to_numpy(np.int64), list(pdf["text"])
    return pdf.iloc[sorted(range(len(pdf)), key=lambda k: (ids[k], texts[k] or b""))].reset_index(drop=True)


class Block:
    """Words of a block's documents as one sequence of numbers, and its windows."""

    def __init__(self, pdf: pd.DataFrame, width: int):
        from xxhash import xxh64_intdigest

        self.ids, self.width = pdf["id"].to_numpy(np.int64), width
        numbers, lengths, parts = _Numbers(), [], []
        for t in pdf["text"]:
            words = (t or b"").split()
            lengths.append(len(words))
            parts.append(np.fromiter(map(numbers.__getitem__, words), np.int32, len(words)))
        self.lengths = np.array(lengths, np.int64)
        self.ends = np.cumsum(self.lengths)
        self.words = list(numbers)
        self.sym = np.concatenate(parts) if parts else np.zeros(0, np.int32)
        h = np.fromiter((xxh64_intdigest(w, 5) for w in self.words), np.uint64, len(self.words))
        self.h = h[self.sym] if len(h) else np.zeros(0, np.uint64)
        n = len(self.sym)
        of = np.repeat(np.arange(len(self.ids)), self.lengths)
        self.starts = np.flatnonzero(np.arange(n) + width <= self.ends[of]) if n else np.zeros(0, np.int64)
        self.doc = self.ids[of[self.starts]]
        run = min(RUN, width)
        low, span, step = _runs(self.h, run), width - run + 1, 1
        while step < span:
            # the least of 2 * step runs, or of all of the window's
            by = min(step, span - step)
            low = np.minimum(low, np.concatenate((low[by:], np.full(min(by, n), np.iinfo(np.uint64).max, np.uint64))))
            step += by
        self.anchor = low[self.starts]

    def nodes(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Order of the windows ``at`` in their tree (by document within a node), and the first of each node."""
        covered = np.zeros(len(self.sym) + 1, np.int64)
        np.add.at(covered, self.starts[at], 1)
        np.add.at(covered, self.starts[at] + self.width, -1)
        held = np.cumsum(covered[:-1]) > 0
        place = np.cumsum(held) - 1
        return subtree(self.sym[held], place[self.starts[at]], self.doc[at], self.width)


def _ranks(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Rank of each pair among all pairs."""
    if not len(a):
        return a
    return np.unique(a.astype(np.int64) * (int(b.max()) + 1) + b, return_inverse=True)[1]


def subtree(sym: np.ndarray, starts: np.ndarray, doc: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """Suffix array over ``starts`` and where a node of ``depth`` words begins in it.

    Ranks of runs double in length, as in prefix doubling; neighbours whose
    common prefix reaches ``depth`` lie below one node.  Suffixes of a node come
    by document, then place.
    """
    ranks, length = sym, 1
    while length * 2 <= depth:
        ranks = _ranks(ranks[: len(ranks) - length], ranks[length:])
        length *= 2
    top = ranks[starts] if length == depth else _ranks(ranks[starts], ranks[starts + depth - length])
    order = np.lexsort((starts, doc, top))
    s = top[order]
    reach = np.concatenate(([False], s[1:] == s[:-1])) if len(s) else np.zeros(0, bool)
    return order, np.flatnonzero(~reach)


def _least(order: np.ndarray, first: np.ndarray) -> np.ndarray:
    """For each suffix of the array, the one that its node begins with."""
    return np.repeat(order[first], np.diff(np.append(first, len(order))))


def _isin(x: np.ndarray, among: np.ndarray) -> np.ndarray:
    """``among`` is sorted."""
    if not len(among):
        return np.zeros(len(x), bool)
    return among[np.minimum(np.searchsorted(among, x), len(among) - 1)] == x


def _deal(split: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Order by bucket, bounds of each bucket, and the buckets that have any."""
    order = np.argsort(split, kind="stable")
    at = np.searchsorted(split[order], np.arange(buckets + 1))
    return order, at, np.flatnonzero(at[1:] > at[:-1])


def _send_anchors(buckets: int, width: int):
    def task(pdf: pd.DataFrame) -> pd.DataFrame:
        v, n = np.unique(Block(pdf, width).anchor, return_counts=True)
        order, at, full = _deal((v % np.uint64(buckets)).astype(np.int64), buckets)
        # windows as a power of two
        size = np.ceil(np.log2(n)).astype(np.uint8)
        parts = [order[at[k] : at[k + 1]] for k in full]
        return pd.DataFrame({"bucket": full, "block": pdf["block"].iloc[0], "v": [v[p].tobytes() for p in parts], "size": [size[p].tobytes() for p in parts]})

    return task


def _meet_anchors(most: int):
    """For each block: its anchors in two blocks or more, those with more than ``most`` windows apart."""

    def task(pdf: pd.DataFrame) -> pd.DataFrame:
        parts = [np.frombuffer(b, "<u8") for b in pdf["v"]]
        v, size = np.concatenate(parts), np.concatenate([np.frombuffer(b, np.uint8) for b in pdf["size"]])
        row = np.repeat(np.arange(len(parts)), list(map(len, parts)))
        order = np.argsort(v, kind="stable")
        s = v[order]
        new = np.concatenate(([True], s[1:] != s[:-1]))
        first, group = np.flatnonzero(new), np.cumsum(new) - 1
        two = np.diff(np.append(first, len(s))) > 1
        heavy = np.add.reduceat(np.ldexp(1.0, size[order].astype(np.int32)), first) > most
        out = {}
        for name, pick in (("few", two & ~heavy), ("many", two & heavy)):
            at = order[pick[group]]
            at.sort()
            cuts = np.searchsorted(row[at], np.arange(len(parts) + 1))
            out[name] = [v[at[cuts[k] : cuts[k + 1]]].tobytes() for k in range(len(parts))]
        made = pd.DataFrame({"block": pdf["block"].to_numpy(), **out})
        return made[(made["few"].str.len() > 0) | (made["many"].str.len() > 0)]

    return task


def _sorted_of(column: pd.Series) -> np.ndarray:
    x = np.frombuffer(b"".join(column), "<u8").copy() if len(column) else np.zeros(0, np.uint64)
    x.sort()
    return x


def _send_suffixes(buckets: int, width: int):
    def task(docs: pd.DataFrame, told: pd.DataFrame) -> pd.DataFrame:
        import zstandard

        if not len(docs) or not len(told):
            return pd.DataFrame({"bucket": [], "block": [], "text": [], "n": [], "doc": [], "at": []})
        docs = _ordered(docs)
        b = Block(docs, width)
        heavy = _isin(b.anchor, _sorted_of(told["many"]))
        at = np.flatnonzero(heavy | _isin(b.anchor, _sorted_of(told["few"])))
        order, first = b.nodes(at)
        own = np.sort(at[order[first]])  # each distinct window of its smallest document here
        # fragments: consecutive windows of one prefix
        anchor, doc = b.anchor[own], b.doc[own]
        cut = (np.diff(b.starts[own]) != 1) | (doc[1:] != doc[:-1]) | (anchor[1:] != anchor[:-1]) | heavy[own][1:]
        head = np.flatnonzero(np.concatenate(([True], cut)))
        n = np.diff(np.append(head, len(own)))
        lead = own[head]
        prefix = np.where(heavy[lead], _runs(b.h, width)[b.starts[lead]], b.anchor[lead])
        deal, bounds, full = _deal((_mix(prefix) % np.uint64(buckets)).astype(np.int64), buckets)
        sym, words, pack = b.sym.tolist(), b.words, zstandard.ZstdCompressor(level=1)
        low = b.starts[lead]
        spans = list(zip(low[deal].tolist(), (low + n + width - 1)[deal].tolist()))
        texts = [b" ".join(map(words.__getitem__, sym[i:j])) for i, j in spans]
        rows = [deal[bounds[k] : bounds[k + 1]] for k in full]
        return pd.DataFrame(
            {
                "bucket": full,
                "block": docs["block"].iloc[0],
                "text": [pack.compress(b" ".join(texts[bounds[k] : bounds[k + 1]])) for k in full],
                "n": [n[r].astype("<i4").tobytes() for r in rows],
                "doc": [b.doc[lead[r]].astype("<i8").tobytes() for r in rows],
                "at": [lead[r].astype("<i4").tobytes() for r in rows],
            }
        )

    return task


def _rows_of_runs(at: np.ndarray, source: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Runs of consecutive windows with one source: first, number, source."""
    head = np.flatnonzero(np.concatenate(([True], (np.diff(at) != 1) | (source[1:] != source[:-1])))) if len(at) else np.zeros(0, np.int64)
    return at[head], np.diff(np.append(head, len(at))), source[head]


def _grow_trees(width: int):
    """For each block: runs of suffixes that start in an earlier document elsewhere, and that document."""

    def task(pdf: pd.DataFrame) -> pd.DataFrame:
        import zstandard

        numbers, sym, unpack = _Numbers(), [], zstandard.ZstdDecompressor()
        for text in pdf["text"]:
            words = unpack.decompress(text).split()
            sym.append(np.fromiter(map(numbers.__getitem__, words), np.int32, len(words)))
        n, doc, at = (np.concatenate([np.frombuffer(x, kind) for x in pdf[c]]) for c, kind in (("n", "<i4"), ("doc", "<i8"), ("at", "<i4")))
        row = np.repeat(np.arange(len(pdf)), [len(x) // 8 for x in pdf["doc"]])
        # suffixes of all fragments, one after the other
        step = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        low = np.cumsum(n + width - 1) - (n + width - 1)
        doc, number, row = np.repeat(doc, n), np.repeat(at, n) + step, np.repeat(row, n)
        order, first = subtree(np.concatenate(sym), np.repeat(low, n) + step, doc, width)
        source = np.empty(len(order), np.int64)
        source[order] = doc[_least(order, first)]
        late = np.flatnonzero(doc > source)
        late = late[np.lexsort((number[late], row[late]))]
        cuts = np.searchsorted(row[late], np.arange(len(pdf) + 1))
        out = []
        for k in range(len(pdf)):
            mine = late[cuts[k] : cuts[k + 1]]
            if len(mine):
                runs = _rows_of_runs(number[mine], source[mine])
                out.append((pdf["block"].iloc[k], *(x.astype(t).tobytes() for x, t in zip(runs, ("<i4", "<i4", "<i8")))))
        return pd.DataFrame(out, columns=["block", "at", "n", "source"])

    return task


def _cut(width: int):
    def task(docs: pd.DataFrame, told: pd.DataFrame) -> pd.DataFrame:
        if not len(docs):
            return pd.DataFrame({"id": [], "n_words": [], "n_removed": [], "kept": [], "repeats": []})
        docs = _ordered(docs)
        b = Block(docs, width)
        source = b.doc.copy()  # the earliest document of each window
        known = np.zeros(0, np.int64)
        if len(told):
            at, n, first = (np.frombuffer(b"".join(told[c]), kind) for c, kind in (("at", "<i4"), ("n", "<i4"), ("source", "<i8")))
            known = np.repeat(at, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            source[known] = np.repeat(first, n)
        # windows that may recur here: an anchor in two documents, or of a window that was told
        order = np.lexsort((b.doc, b.anchor))
        a, d = b.anchor[order], b.doc[order]
        again = a[1:][(a[1:] == a[:-1]) & (d[1:] != d[:-1])]
        some = np.flatnonzero(_isin(b.anchor, np.unique(np.concatenate((again, b.anchor[known])))))
        if len(some):
            order, first = b.nodes(some)
            # the first of a node has its smallest document here, so it is the one that was told
            source[some[order]] = source[some[_least(order, first)]]
        gone = np.flatnonzero(source < b.doc)
        change = np.zeros(len(b.sym) + 1, np.int64)
        np.add.at(change, b.starts[gone], 1)
        np.add.at(change, b.starts[gone] + width, -1)
        lost = np.cumsum(change[:-1]) > 0
        place, n, where = _rows_of_runs(b.starts[gone], source[gone])
        of = np.searchsorted(b.ends, place, side="right")
        kept, removed, repeats = [], [], []
        cuts = np.searchsorted(of, np.arange(len(b.ids) + 1))
        for k, (text, end, size) in enumerate(zip(docs["text"], b.ends.tolist(), b.lengths.tolist())):
            own = lost[end - size : end]
            words = (text or b"").split()
            removed.append(int(own.sum()))
            kept.append(b" ".join(words if not removed[-1] else [w for w, x in zip(words, own.tolist()) if not x]).decode("utf-8", "replace"))
            mine = slice(cuts[k], cuts[k + 1])
            repeats.append([{"start": s - (end - size), "length": m + width - 1, "first_doc": f} for s, m, f in zip(place[mine].tolist(), n[mine].tolist(), where[mine].tolist())])
        return pd.DataFrame({"id": docs["id"], "n_words": b.lengths, "n_removed": removed, "kept": kept, "repeats": repeats})

    return task


REPEATS = "array<struct<start:long,length:long,first_doc:long>>"


def dedup_substrings(docs: DataFrame, width: int = WIDTH, subtree_size: int = SUBTREE) -> DataFrame:
    """(doc_id, n_words, n_removed, kept, repeats) of every row; ``kept`` joins the words that stay by one space.

    A word goes where a window of ``width`` words of its document covers it
    whose word sequence also starts in a document with a smaller doc_id.
    ``repeats`` are the maximal runs of such windows with one earliest document:
    first word, words, that document.  Null and empty texts have no words.  Rows
    with a null doc_id lose nothing and take nothing from others; rows that
    share an id count as one document for each other and are judged each.
    Other columns are not read.  An empty table gives no rows.
    ``subtree_size`` is how many suffixes a prefix may have before it grows to
    the whole window; it changes no result.
    """
    spark = docs.sparkSession
    ship(spark)
    least, size = int(spark.conf.get("spark.sql.shuffle.partitions")), plan_bytes(docs.select("doc_id", "text"), "text")
    n, n_anchors, n_trees = (max(least, size // b) for b in (BLOCK_BYTES, ANCHOR_BYTES, TREE_BYTES))
    rows = docs.select(F.col("doc_id").cast("long").alias("id"), F.col("text").cast("binary").alias("text"))
    known = rows.where("id is not null").withColumn("block", F.pmod(F.xxhash64("id"), F.lit(n)).cast("int")).repartition(n, "block")
    anchors = known.groupBy("block").applyInPandas(_send_anchors(n_anchors, width), "bucket int, block int, v binary, size binary")
    told = anchors.repartition(n_anchors, "bucket").groupBy("bucket").applyInPandas(_meet_anchors(subtree_size), "block int, few binary, many binary")
    suffixes = known.groupBy("block").cogroup(told.groupBy("block")).applyInPandas(_send_suffixes(n_trees, width), "bucket int, block int, text binary, n binary, doc binary, at binary")
    late = suffixes.repartition(n_trees, "bucket").groupBy("bucket").applyInPandas(_grow_trees(width), "block int, at binary, n binary, source binary")
    cut = known.groupBy("block").cogroup(late.groupBy("block")).applyInPandas(_cut(width), f"id long, n_words long, n_removed long, kept string, repeats {REPEATS}")
    words = F.regexp_extract_all(F.coalesce(F.col("text").cast("string"), F.lit("")), F.lit(r"[^\x20\x09-\x0D]++"), F.lit(0))
    unnamed = rows.where("id is null").select("id", F.size(words).cast("long").alias("n_words"), F.lit(0).cast("long").alias("n_removed"), F.array_join(words, " ").alias("kept"), F.array().cast(REPEATS).alias("repeats"))
    return cut.unionByName(unnamed).withColumnRenamed("id", "doc_id")


def digest(docs: DataFrame) -> DataFrame:
    return dedup_substrings(docs).select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept").cast("binary"), 256).alias("kept_sha256"))


ORACLE = r"""
WITH w AS (
  SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents
), win AS (
  SELECT doc_id, unnest(range(1, len(ws) - 11)) AS i, ws FROM w WHERE len(ws) >= 13
), keyed AS (
  SELECT doc_id, i, array_to_string(ws[i:i + 12], ' ') AS k FROM win
), firsts AS (
  SELECT k, min(doc_id) AS m FROM keyed GROUP BY k HAVING min(doc_id) < max(doc_id)
), late AS (
  SELECT DISTINCT doc_id, i FROM keyed JOIN firsts USING (k) WHERE doc_id > m
), gone AS (
  SELECT DISTINCT doc_id, i + o AS j FROM late, (SELECT unnest(range(13)) AS o)
), words AS (
  SELECT doc_id, unnest(range(1, len(ws) + 1)) AS j, unnest(ws) AS word FROM w
)
SELECT d.doc_id, count(words.j) AS n_words, count(gone.j) AS n_removed,
  sha256(coalesce(string_agg(word, ' ' ORDER BY words.j) FILTER (gone.j IS NULL), '')) AS kept_sha256
FROM documents d LEFT JOIN words ON words.doc_id = d.doc_id LEFT JOIN gone ON gone.doc_id = words.doc_id AND gone.j = words.j
GROUP BY d.doc_id
"""
