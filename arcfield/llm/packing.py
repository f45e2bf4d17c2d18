"""Mixture-controlled packing by deficit round-robin over source queues.

Targets are the token shares of the sources over all documents.  Texts are
encoded once and cut into chunks, which are dealt by hash, so each task sees
every source, whatever the order and lengths of the documents.  It queues the
tokens of a block by source; each window adds every source's share to its
deficit and serves each source its deficit, the one that is owed most first; a
source that is owed less than a quantum waits for a later window.  Where a
source that is due has run dry, the others wait for the next block.  What a
source is owed or has overdrawn passes to the next window and block; at the
end of a task the last tokens of all queues and the deficits of all sources
pass on to a second round, which packs the tails of many tasks together and
spreads the deficits over its windows.  Only a tail group's last window is
padded.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from arcfield.deploy import plan_bytes, save, ship
from arcfield.llm.tokens import encoder, read_tokenizer, tidy

WINDOW, QUANTUM, BLOCK = 2048, 64, 1 << 20
#: Tokens of a document that are dealt together; blocks that may wait for a source that is due.
CHUNK, WAIT = 1 << 13, 4
#: Tasks whose tails are packed together, and windows a tail may have: at most TAILS * TAIL * WINDOW tokens.
TAILS, TAIL = 8, 256
CUT = "doc_id long, source string, start long, length long, doc_tokens long, ids binary"
CUT_COLUMNS = [c.split()[0] for c in CUT.split(", ")]
PIECE = "doc_id long, source string, start long, length long, doc_tokens long, sequence_id long, offset long, part int, owed double, ids binary"


class Packer:
    """Queues, deficits and the open window of one task."""

    def __init__(self, window: int, quantum: int, shares: dict, first_sequence: int):
        total = sum(shares.values()) or 1.0
        self.window, self.quantum, self.shares = window, quantum, {s: w / total for s, w in shares.items()}
        self.queues: dict = {}
        self.size: dict = {}
        self.owed: dict = {}
        self.total, self.sequence = 0, first_sequence

    def add(self, doc_id, source, start: int, doc_tokens: int, ids: np.ndarray) -> None:
        if len(ids):
            self.queues.setdefault(source, deque()).append([doc_id, start, doc_tokens, ids])
            self.size[source] = self.size.get(source, 0) + len(ids)
            self.total += len(ids)

    def _dry(self) -> bool:
        """Whether a source lacks a quantum or more of what the next window owes it."""
        return any(self.size.get(s, 0) + self.quantum <= self.owed.get(s, 0.0) + w * self.window for s, w in self.shares.items())

    def _take(self, source, most: int):
        head = self.queues[source][0]
        doc_id, start, doc_tokens, ids = head
        n = min(most, len(ids))
        if n == len(ids):
            self.queues[source].popleft()
        else:
            head[1], head[3] = start + n, ids[n:]
        self.size[source] -= n
        self.total -= n
        return doc_id, source, start, n, doc_tokens, ids[:n]

    def windows(self, *, last: bool = False, wait: int = 0):
        """Pieces of every full window; with ``last`` of the unfilled one too.

        Up to ``wait`` tokens stay in their queues while a source that is due has run dry.
        """
        while self.total >= self.window or last and self.total:
            if self.total <= wait and self._dry():
                break
            room = min(self.window, self.total)
            for s, w in self.shares.items():
                self.owed[s] = self.owed.get(s, 0.0) + w * room
            offset = 0
            for source, due in self._allot(room):
                self.owed[source] = self.owed.get(source, 0.0) - due
                while due:
                    piece = self._take(source, due)
                    yield (*piece[:5], self.sequence, offset, piece[5])
                    offset += piece[3]
                    due -= piece[3]
            self.sequence += 1

    def _allot(self, room: int) -> list[tuple]:
        """(source, tokens) for a window of ``room`` tokens: what each is owed, then quanta to those owed most."""
        live = sorted((s for s, n in self.size.items() if n), key=lambda s: (-self.owed.get(s, 0.0), s or ""))
        given = {}
        for s in live:
            due = min(int(self.owed.get(s, 0.0)), self.size[s], room)
            given[s] = due if due >= min(self.quantum, self.size[s]) else 0
            room -= given[s]
        # those that wait leave room, as do fractions of a token
        while room:
            s = max((s for s in live if self.size[s] > given[s]), key=lambda s: self.owed.get(s, 0.0) - given[s])
            n = min(room, self.quantum, self.size[s] - given[s])
            given[s] += n
            room -= n
        return [(s, n) for s, n in given.items() if n]

    def rest(self):
        """What no window took, and a row without tokens for each source with what it is owed."""
        for s, q in self.queues.items():
            for doc_id, start, doc_tokens, ids in q:
                yield doc_id, s, start, len(ids), doc_tokens, ids, None
        for s, owed in self.owed.items():
            yield None, s, None, 0, None, np.zeros(0, "<u4"), owed


SCHEMA = pa.schema([(c, {"long": pa.int64(), "int": pa.int32(), "double": pa.float64(), "string": pa.string(), "binary": pa.binary()}[t]) for c, t in (x.split() for x in PIECE.split(", "))])


def _rows(pieces, part: int) -> pa.RecordBatch:
    """Pieces of windows as Arrow columns."""
    d, s, st, n, t, q, o, ids = zip(*pieces) if (pieces := list(pieces)) else [()] * 8
    columns = [d, s, st, n, t, q, o, [part] * len(d), [None] * len(d), [x.astype("<u4").tobytes() for x in ids]]
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, SCHEMA)], schema=SCHEMA)


def _tail(pieces, part: int) -> pa.RecordBatch:
    """What a task leaves, with what each source is owed and no window."""
    d, s, st, n, t, ids, owed = zip(*pieces) if (pieces := list(pieces)) else [()] * 7
    none = [None] * len(d)
    columns = [d, s, st, n, t, none, none, [part] * len(d), owed, [x.astype("<u4").tobytes() for x in ids]]
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, SCHEMA)], schema=SCHEMA)


def pack(docs: DataFrame, tokenizer_path: str, *, eos: int = 1, window: int = WINDOW, quantum: int = QUANTUM, shares: dict[str, float] | None = None) -> DataFrame:
    """Pieces of all documents: (doc_id, source, start, length, doc_tokens, sequence_id, offset, ids).

    Every id of every document (null text: just ``eos``) is in exactly one
    piece; ids are little-endian unsigned 32-bit integers.  ``shares`` are
    target token proportions by source; by default those of all documents, so
    that no source runs dry early.  A null source is a source of its
    own; null ids and repeated rows are packed like others.  Columns other
    than doc_id, source and text are not read.  An empty table has no pieces.
    """
    spark = docs.sparkSession
    ship(spark)
    content = spark.sparkContext.broadcast(read_tokenizer(tokenizer_path))
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), "text")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(content.value)
        end, schema = np.array([eos], enc.dtype), pa.schema([(f.name, f.type) for f in SCHEMA if f.name in CUT_COLUMNS])
        rows, waiting = [], 0

        def batch_of(rows):
            return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), schema)], schema=schema)

        for batch in batches:
            ids, sources, texts = batch.columns
            for i, s, tokens in zip(ids.to_pylist(), sources.to_pylist(), enc.encode_arrow(texts)):
                tokens = np.concatenate((tokens, end))
                for k in range(0, len(tokens), CHUNK):
                    piece = tokens[k : k + CHUNK]
                    rows.append((i, s, k, len(piece), len(tokens), piece.tobytes()))
                waiting += len(tokens)
                if waiting >= BLOCK:
                    yield batch_of(rows)
                    rows, waiting = [], 0
        if rows:
            yield batch_of(rows)
        tidy()

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        packer, waiting = Packer(window, quantum, shares, part << 32), 0
        for batch in batches:
            for i, s, start, length, doc_tokens, ids in zip(*(c.to_pylist() for c in batch.columns)):
                packer.add(i, s, start, doc_tokens, np.frombuffer(ids, f"<u{len(ids) // length}"))
                waiting += length
                if waiting >= BLOCK:
                    yield _rows(packer.windows(wait=WAIT * BLOCK), part)
                    waiting = 0
        yield _rows(packer.windows(wait=TAIL * window), part)
        yield _tail(packer.rest(), part)

    def second(pieces: pa.Table) -> pa.Table:
        rows = pieces.to_pylist()
        group = rows[0]["part"] // TAILS
        # what the sources are owed is spread over all windows of the tail
        left, total = sum(r["length"] for r in rows), sum(shares.values()) or 1.0
        due = {s: left * w / total for s, w in shares.items()}
        for r in sorted((r for r in rows if not r["length"]), key=lambda r: (r["part"], r["source"] or "")):
            due[r["source"]] = due.get(r["source"], 0.0) + r["owed"]
        packer = Packer(window, quantum, {s: max(0.0, n) for s, n in due.items()}, (group + (1 << 30)) << 32)
        for r in sorted((r for r in rows if r["length"]), key=lambda r: (r["part"], r["source"] or "", -1 if r["doc_id"] is None else r["doc_id"], r["start"])):
            packer.add(r["doc_id"], r["source"], r["start"], r["doc_tokens"], np.frombuffer(r["ids"], "<u4"))
        return pa.Table.from_batches([_rows(packer.windows(last=True), group)])

    n = max(int(spark.conf.get("spark.sql.shuffle.partitions")), plan_bytes(docs, "text") >> 26)
    chunks = save(docs.mapInArrow(cut, CUT), "chunks")
    if shares is None:
        # one row a source
        shares = {r.source: float(r.n) for r in chunks.groupBy("source").agg(F.sum("length").alias("n")).collect()}
    dealt = chunks.withColumn("h", F.xxhash64("doc_id", "start", F.lit(11))).repartition(n, "h").sortWithinPartitions("h", "doc_id", "start").drop("h")
    made = save(dealt.mapInArrow(first, PIECE), "pieces")
    tails = made.where("sequence_id is null").withColumn("tail", F.floor(F.col("part") / TAILS)).repartitionByRange(-(-n // TAILS), "tail")
    tails = tails.groupBy("tail").applyInArrow(second, PIECE)
    return made.where("sequence_id is not null").unionByName(tails).drop("part", "owed")


def digest(docs: DataFrame, tokenizer_path: str) -> DataFrame:
    out = pack(docs, tokenizer_path)
    return out.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset", "source")
