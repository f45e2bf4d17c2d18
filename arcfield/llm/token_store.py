"""Binary token output: each document compressed alone under one shared zstandard dictionary.

A store is a folder with two tables.  ``dictionary`` has one row: hash and
bytes of the dictionary, trained on serialized id arrays of a bounded sample.
``chunks`` has rows of up to CHUNK_DOCS documents in ascending id order:
shard, chunk, the ids of its documents, their token counts, the byte offset of
each frame, the frames themselves, and the dictionary's hash.  A single
document is read by its offset without touching its neighbours.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from arcfield.deploy import plan_bytes, scratch, ship
from arcfield.llm.tokens import encoder, read_tokenizer, tidy

CHUNK_DOCS, CHUNK_BYTES, GROUP_BYTES = 256, 192 << 10, 16 << 20
#: Dictionary sample: documents, ids of each, and the dictionary's bytes.
SAMPLE_DOCS, SAMPLE_IDS, DICT_BYTES = 1000, 8192, 64 << 10
CHUNKS = "shard int, chunk int, base long, doc_ids array<long>, counts array<long>, offsets array<long>, frames binary, dict_hash string, width int"
SCHEMA = pa.schema([("shard", pa.int32()), ("chunk", pa.int32()), ("base", pa.int64()), ("doc_ids", pa.list_(pa.int64())), ("counts", pa.list_(pa.int64())), ("offsets", pa.list_(pa.int64())), ("frames", pa.binary()), ("dict_hash", pa.string()), ("width", pa.int32())])


def train_dictionary(docs: DataFrame, content, eos: int) -> bytes:
    """Dictionary bytes from at most SAMPLE_DOCS documents chosen by hash; empty where there is too little to learn."""
    import zstandard

    # few rows reach the order: about four times as many as it keeps
    h, most = F.xxhash64("doc_id"), min((1 << 63) - 1, -(1 << 63) + (4 * SAMPLE_DOCS << 64) // max(1, docs.count()))
    picked = docs.where(h <= F.lit(most)).orderBy(h, "doc_id", "text").limit(SAMPLE_DOCS).select("text")

    def ids(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        enc = encoder(content.value)
        for pdf in batches:
            yield pd.DataFrame({"b": [x[:SAMPLE_IDS].tobytes() for x in enc.encode_many(pdf["text"])]})

    samples = [bytes(r.b) for r in picked.mapInPandas(ids, "b binary").orderBy("b").collect() if r.b]
    if sum(map(len, samples)) < 8 * DICT_BYTES or len(samples) < 16:
        return b""
    try:
        return zstandard.train_dictionary(DICT_BYTES, samples).as_bytes()
    except zstandard.ZstdError:
        return b""


def write_tokens(docs: DataFrame, path: str, tokenizer_path: str, eos: int) -> str:
    """Encode every whole text (null: empty), append ``eos``, store in ascending doc_id order under ``path``.

    Rows with a null doc_id come first; rows that share an id stay side by
    side.  Columns other than doc_id and text are not read.
    """
    spark = docs.sparkSession
    ship(spark)
    content = spark.sparkContext.broadcast(read_tokenizer(tokenizer_path))
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    trained = train_dictionary(docs, content, eos)
    mark = hashlib.sha256(trained).hexdigest()
    spark.createDataFrame([(mark, bytearray(trained))], "dict_hash string, data binary").coalesce(1).write.parquet(f"{path}/dictionary")

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard
        from pyspark import TaskContext

        shard = TaskContext.get().partitionId()
        enc = encoder(content.value)
        end = np.array([eos], enc.dtype)
        extra = {}
        if trained:
            extra["dict_data"] = zstandard.ZstdCompressionDict(trained)
            extra["dict_data"].precompute_compress(level=3)
        press = zstandard.ZstdCompressor(level=3, write_content_size=True, **extra)
        chunk = base = 0
        ids, counts, frames, size = [], [], [], 0

        def row() -> pa.RecordBatch:
            offsets = np.concatenate(([0], np.cumsum(np.fromiter(map(len, frames), np.int64, len(frames)))))
            values = (shard, chunk, base, ids, counts, offsets.tolist(), b"".join(frames), mark, enc.dtype.itemsize)
            return pa.RecordBatch.from_arrays([pa.array([v], f.type) for v, f in zip(values, SCHEMA)], schema=SCHEMA)

        for batch in batches:
            for i, tokens in zip(batch.column(0).to_pylist(), enc.encode_arrow(batch.column(1))):
                ids.append(i)
                counts.append(len(tokens) + 1)
                frames.append(press.compress(np.concatenate((tokens, end)).tobytes()))
                size += len(frames[-1])
                if len(ids) >= CHUNK_DOCS or size >= CHUNK_BYTES:
                    yield row()
                    chunk, base = chunk + 1, base + sum(counts)
                    ids, counts, frames, size = [], [], [], 0
        if ids:
            yield row()
        tidy()

    n = max(int(spark.conf.get("spark.sql.shuffle.partitions")), plan_bytes(docs, "text") >> 27)
    # rows of one id, or of none, may be many: they are ranged by text and row as well
    keys = (F.col("doc_id").asc_nulls_first(), F.col("h"), F.col("tie"))
    dealt = docs.withColumn("h", F.xxhash64("text")).withColumn("tie", F.monotonically_increasing_id())
    dealt = dealt.repartitionByRange(n, *keys).sortWithinPartitions(*keys).select("doc_id", "text")
    dealt.mapInArrow(encode, CHUNKS).write.option("compression", "none").options(**{"parquet.block.size": GROUP_BYTES, "parquet.page.size.row.check.min": 4, "parquet.block.size.row.check.min": 16, "parquet.enable.dictionary": "false"}).parquet(f"{path}/chunks")
    return path


def read_tokens(spark: SparkSession, path: str, doc_ids: list[int] | None = None) -> DataFrame:
    """(doc_id, start, n_tokens, ids): ids as little-endian unsigned 32-bit integers; ``start`` counts all tokens before.

    With ``doc_ids`` only the frames of those documents are decompressed.
    """
    ship(spark)
    trained = {r.dict_hash: bytes(r.data) for r in spark.read.parquet(f"{path}/dictionary").collect()}
    chunks = spark.read.schema(CHUNKS).parquet(f"{path}/chunks")
    # one row a shard: as many as the store has partitions
    totals = chunks.select("shard", F.aggregate("counts", F.lit(0).cast("long"), lambda a, b: a + b).alias("n")).groupBy("shard").agg(F.sum("n").alias("n")).orderBy("shard").collect()
    before, total = {}, 0
    for r in totals:
        before[r.shard], total = total, total + r.n
    only = None if doc_ids is None else frozenset(doc_ids)
    if only is not None:
        chunks = chunks.where(F.arrays_overlap("doc_ids", F.array(*[F.lit(int(i)) for i in only])))

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        open_: dict[str, zstandard.ZstdDecompressor] = {}
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.binary())
        for batch in batches:
            for k in range(batch.num_rows):
                shard, _, base, ids, counts, offsets, frames, mark, width = (c[k].as_py() for c in batch.columns)
                if mark not in open_:
                    data = trained[mark]
                    if hashlib.sha256(data).hexdigest() != mark:
                        raise ValueError("the dictionary is not the one the frames were written with")
                    open_[mark] = zstandard.ZstdDecompressor(**({"dict_data": zstandard.ZstdCompressionDict(data)} if data else {}))
                start, out = before[shard] + base, []
                for i, n, a, b in zip(ids, counts, offsets, offsets[1:]):
                    if only is None or i in only:
                        raw = open_[mark].decompress(frames[a:b])
                        out.append((i, start, n, np.frombuffer(raw, f"<u{width}").astype("<u4").tobytes()))
                    start += n
                columns = zip(*out) if out else [()] * 4
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds)], names=["doc_id", "start", "n_tokens", "ids"])

    return chunks.mapInArrow(decode, "doc_id long, start long, n_tokens long, ids binary")


def digest(docs: DataFrame, tokenizer_path: str, eos: int = 2) -> DataFrame:
    spark = docs.sparkSession
    path = write_tokens(docs, scratch(spark, "token-store"), tokenizer_path, eos)
    return read_tokens(spark, path).select("doc_id", "start", "n_tokens", F.crc32("ids").alias("ids_crc32"))
