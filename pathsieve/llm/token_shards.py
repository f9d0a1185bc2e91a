"""Token ids in shards: each document compressed alone with a shared trained zstandard dictionary."""

from __future__ import annotations

import hashlib
import os
import struct
import zlib

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathsieve.llm import kernels as K
from pathsieve.llm.word_codes import WordCodes
from pathsieve.loop import new_path

MAGIC, VERSION = b"PSTOKENS", 1
SHARD_BYTES = 4 << 20
DICTIONARY_BYTES, SAMPLE_DOCS, SAMPLE_TOKENS = 64 << 10, 512, 4096
_HEAD = struct.Struct("<8sHxx32sQ")
_codes: dict[str, WordCodes] = {}


def word_codes(path: str) -> WordCodes:
    """This process's encoder for a tokenizer file whose pre-tokens never span white space.

    Its normalizer maps white space to a separator that the pre-tokenizer drops, so a text's ids are those of its
    words (runs without ASCII white space) one after the other; the library encodes each distinct word.
    """
    if path not in _codes:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        model = Tokenizer.from_file(path)
        _codes[path] = WordCodes(lambda ws: [e.ids for e in model.encode_batch_fast([w.decode() for w in ws], add_special_tokens=False)])
    return _codes[path]


def encoded(column: pa.Array, path: str, end_id: int | None):
    """For each chunk of rows: its range, all ids, and row offsets into them."""
    data, offsets = K.flat(column)
    for i, j in K.chunks(offsets, 4 << 20):
        b = data[offsets[i] : offsets[j]]
        ids, rows = word_codes(path).of(b, *K.words(b, offsets[i : j + 1] - offsets[i], K.NOT_SPACE))
        if end_id is not None:
            ids = np.insert(ids, rows[1:], end_id)
            rows = rows + np.arange(len(rows))
        yield i, j, ids.astype("<u4"), rows


def pack(documents: list[bytes], dictionary: bytes, level: int = 3) -> bytes:
    """One shard: header, offset index (n + 1 numbers), then a frame for each document."""
    shared = zstandard.ZstdCompressionDict(dictionary) if dictionary else None
    press = zstandard.ZstdCompressor(level=level, dict_data=shared, write_dict_id=False)
    frames = [press.compress(d) for d in documents]
    index = np.concatenate([[0], np.cumsum([len(f) for f in frames])]).astype("<u8")
    return _HEAD.pack(MAGIC, VERSION, hashlib.sha256(dictionary).digest(), len(documents)) + index.tobytes() + b"".join(frames)


class ShardReader:
    """Random access to the documents of one packed shard."""

    def __init__(self, image: bytes, dictionary: bytes) -> None:
        magic, version, digest, self.n = _HEAD.unpack_from(image)
        if magic != MAGIC or version != VERSION:
            raise ValueError("not a token shard of this version")
        if digest != hashlib.sha256(dictionary).digest():
            raise ValueError("the shard was written with another dictionary")
        self._image = memoryview(image)
        self._index = np.frombuffer(image, "<u8", self.n + 1, _HEAD.size)
        self._at = _HEAD.size + 8 * (self.n + 1)
        shared = zstandard.ZstdCompressionDict(dictionary) if dictionary else None
        self._expand = zstandard.ZstdDecompressor(dict_data=shared)

    def __len__(self) -> int:
        return self.n

    def raw(self, k: int) -> bytes:
        """The k-th document's ids as little-endian unsigned 32-bit integers."""
        return self._expand.decompress(self._image[self._at + int(self._index[k]) : self._at + int(self._index[k + 1])])


def train_dictionary(samples: list[bytes], size: int = DICTIONARY_BYTES) -> bytes:
    """A dictionary from serialized id arrays; empty where there is too little to learn from."""
    try:
        return zstandard.train_dictionary(size, [s for s in samples if s]).as_bytes()
    except (zstandard.ZstdError, ValueError):
        return b""


def _write(batches, path: str, end_id: int | None, dictionary: bytes, shard_bytes: int):
    part, number, start = TaskContext.get().partitionId(), 0, 0
    ids, documents, held, tokens, id_type = [], [], 0, 0, None

    def shard():
        return pa.RecordBatch.from_arrays([
            pa.array([part], pa.int32()), pa.array([number], pa.int32()), pa.array([start], pa.int64()), pa.array([tokens], pa.int64()),
            pa.array([ids], pa.list_(id_type)), pa.array([pack(documents, dictionary)], pa.binary()),
        ], names=["part", "number", "part_start", "n_tokens", "doc_ids", "image"])

    for batch in batches:
        id_type, names = batch.schema.field("doc_id").type, batch.column("doc_id").to_pylist()
        for i, j, flat, rows in encoded(batch.column("text"), path, end_id):
            for k in range(j - i):
                raw = flat[rows[k] : rows[k + 1]].tobytes()
                ids.append(names[i + k])
                documents.append(raw)
                held, tokens = held + len(raw), tokens + len(raw) // 4
                if held >= shard_bytes:
                    yield shard()
                    number, start = number + 1, start + tokens
                    ids, documents, held, tokens = [], [], 0, 0
    if documents:
        yield shard()


def _read(batches, dictionary: bytes):
    for batch in batches:
        for start, names, image in zip(batch.column("start").to_pylist(), batch.column("doc_ids").to_pylist(), batch.column("image"), strict=True):
            reader = ShardReader(image.as_py(), dictionary)
            rows = [reader.raw(k) for k in range(len(reader))]
            n = np.array([len(r) // 4 for r in rows], np.int64)
            yield pa.RecordBatch.from_arrays([
                pa.array(names, batch.schema.field("doc_ids").type.value_type), pa.array(start + np.cumsum(n) - n), pa.array(n), pa.array([zlib.crc32(r) for r in rows], pa.int64()),
            ], names=["doc_id", "start", "n_tokens", "ids_crc32"])


def write_shards(docs: DataFrame, tokenizer: str, path: str, end_id: int | None = 2, shard_bytes: int = SHARD_BYTES) -> bytes:
    """Encode ``docs`` (doc_id, text) and write shards in ascending doc_id order under ``path``.

    Each shard is an image in the format of :func:`pack` with about ``shard_bytes`` of ids; images lie as
    binary values in Parquet, so any store that Spark can write to holds them and a lost task is
    written again. The dictionary, stored beside them, is trained on at most SAMPLE_DOCS documents of the least
    hashes, SAMPLE_TOKENS ids of each; it has at most DICTIONARY_BYTES and is returned.
    Null and empty texts hold the end id alone. Rows that repeat a doc_id follow each other by text hash.
    """
    spark = docs.sparkSession
    order = F.xxhash64(F.col("doc_id"), F.lit(4))
    ids = docs.select("doc_id").where("doc_id IS NOT NULL").distinct().orderBy(order, "doc_id").limit(SAMPLE_DOCS)
    sample = docs.select("doc_id", "text").join(F.broadcast(ids), "doc_id", "left_semi").dropDuplicates(["doc_id"])
    short = sample.select("doc_id", F.substring("text", 1, SAMPLE_TOKENS * 4).alias("text")).orderBy("doc_id").toArrow()
    raw = [flat[s:e][:SAMPLE_TOKENS].tobytes() for _, _, flat, rows in encoded(short.column("text"), tokenizer, end_id) for s, e in zip(rows[:-1], rows[1:], strict=True)]
    dictionary = train_dictionary(raw)
    ordered = docs.select("doc_id", "text", F.xxhash64("text").alias("h")).repartitionByRange("doc_id", "h").sortWithinPartitions("doc_id", "h").drop("h")
    shards = ordered.mapInArrow(lambda it: _write(it, tokenizer, end_id, dictionary, shard_bytes), f"part int, number int, part_start long, n_tokens long, doc_ids array<{dict(docs.dtypes)['doc_id']}>, image binary")
    shards.write.option("compression", "none").parquet(f"{path}/shards")
    spark.createDataFrame([(hashlib.sha256(dictionary).hexdigest(), dictionary)], "digest string, dictionary binary").coalesce(1).write.parquet(f"{path}/dictionary")
    return dictionary


def read_shards(spark, path: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every document in the shards under ``path``.

    Positions need only the tokens of each written partition, one number each.
    """
    dictionary = bytes(spark.read.parquet(f"{path}/dictionary").first()["dictionary"])
    shards = spark.read.parquet(f"{path}/shards")
    totals = sorted((r[0], r[1]) for r in shards.groupBy("part").agg(F.sum("n_tokens")).collect())
    starts, at = [], 0
    for part, n in totals:
        starts.append((part, at))
        at += n
    offsets = spark.createDataFrame(starts, "part int, before long")
    placed = shards.join(F.broadcast(offsets), "part").select((F.col("before") + F.col("part_start")).alias("start"), "doc_ids", "image")
    id_type = dict(shards.dtypes)["doc_ids"].removeprefix("array<").removesuffix(">")
    return placed.mapInArrow(lambda it: _read(it, dictionary), f"doc_id {id_type}, start long, n_tokens long, ids_crc32 long")


def token_shards(docs: DataFrame, tokenizer: str, end_id: int = 2) -> DataFrame:
    """Write the shards of ``docs`` to a new folder on shared storage and read them back."""
    path = new_path(docs.sparkSession, "tokens")
    write_shards(docs, tokenizer, path, end_id)
    return read_shards(docs.sparkSession, path)
