"""Token files of directly addressable codes.

An id is cut into chunks of `bits` bits.  Level 0 holds the lowest chunk of
every id, level k the k-th chunk of the ids that have one; a bitmap beside each
level says which entries continue, and a rank directory (ones before every block
of 512 bits) leads from an entry to its place one level up.  Any id, or any run
of ids, is read by rank and a look at one place per level: nothing else is
decoded.

A file image holds whole documents: header, document ids, token offsets, levels.
Images are the rows of a Parquet table (part, seq, first position, payload), so
Spark's committer makes the write atomic and repeatable after lost executors and
any store that Spark can reach will do; `export` gives the bytes of one image.

Order is ascending document id over the range partitions; positions are global
after adding the token totals of the earlier parts (one short row a part).

Defined cases: null text is an empty document (the end id only); a null id
sorts first and stays null; repeated ids are separate documents, by text hash and text; an empty
table gives no image and no row; one very long document is one image.
"""

from __future__ import annotations

import struct
import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from .common import shared_folder
from .tokens import encoder, slices, with_end

MAGIC = b"DAC1"
BLOCK = 512
NO_ID = -(1 << 63)
IMAGE_TOKENS = 1 << 20


# --- the code itself ---------------------------------------------------------


def encode_levels(ids: np.ndarray, bits: int = 8) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Levels of (chunks, bitmap bytes, rank directory)."""
    levels = []
    left = ids.astype(np.uint64)
    mask = np.uint64((1 << bits) - 1)
    while True:
        chunk = (left & mask).astype(np.uint8 if bits <= 8 else np.uint16)
        left = left >> np.uint64(bits)
        more = left > 0
        bitmap = np.packbits(more, bitorder="little")
        padded = np.zeros(-(-len(more) // BLOCK) * BLOCK // 8, np.uint8)
        padded[: len(bitmap)] = bitmap
        ones = np.bitwise_count(padded).reshape(-1, BLOCK // 8).sum(axis=1, dtype=np.uint64)
        levels.append((chunk, bitmap, np.cumsum(ones) - ones))
        if not more.any():
            return levels
        left = left[more]


def image(doc_ids: np.ndarray, offsets: np.ndarray, ids: np.ndarray, bits: int = 8) -> bytes:
    """One self-describing file image."""
    levels = encode_levels(ids, bits)
    out = [MAGIC, struct.pack("<IIQQ", bits, len(levels), len(doc_ids), len(ids)), doc_ids.astype("<i8").tobytes(), offsets.astype("<u8").tobytes()]
    for chunk, bitmap, directory in levels:
        out += [struct.pack("<Q", len(chunk)), directory.astype("<u8").tobytes(), chunk.astype("<u1" if bits <= 8 else "<u2").tobytes(), bitmap.tobytes()]
    return b"".join(out)


class Image:
    """Random access to a file image, without decoding it."""

    def __init__(self, data: bytes):
        if data[:4] != MAGIC:
            raise ValueError("not a token file")
        self.bits, n_levels, n_docs, self.n_tokens = struct.unpack_from("<IIQQ", data, 4)
        at = 4 + struct.calcsize("<IIQQ")
        self.doc_ids = np.frombuffer(data, "<i8", n_docs, at)
        at += 8 * n_docs
        self.offsets = np.frombuffer(data, "<u8", n_docs + 1, at).astype(np.int64)
        at += 8 * (n_docs + 1)
        self.levels = []
        kind, width = ("<u1", 1) if self.bits <= 8 else ("<u2", 2)
        for _ in range(n_levels):
            (n,) = struct.unpack_from("<Q", data, at)
            at += 8
            directory = np.frombuffer(data, "<u8", -(-n // BLOCK), at)
            at += 8 * len(directory)
            chunk = np.frombuffer(data, kind, n, at)
            at += width * n
            bitmap = np.frombuffer(data, np.uint8, -(-n // 8), at)
            at += len(bitmap)
            self.levels.append((chunk, bitmap, directory))

    def rank(self, level: int, i: int) -> int:
        """Continuing entries before entry i: one directory entry and less than a block of bits."""
        chunk, bitmap, directory = self.levels[level]
        if i >= len(chunk):
            return int(directory[-1]) + self._ones(bitmap, (len(directory) - 1) * BLOCK, len(chunk)) if len(chunk) else 0
        block = i // BLOCK
        return int(directory[block]) + self._ones(bitmap, block * BLOCK, i)

    @staticmethod
    def _ones(bitmap: np.ndarray, a: int, b: int) -> int:
        full = int(np.bitwise_count(bitmap[a // 8 : b // 8]).sum())
        return full + (int(bitmap[b // 8] & ((1 << b % 8) - 1)).bit_count() if b % 8 else 0)

    def __getitem__(self, i: int) -> int:
        """One id."""
        if not 0 <= i < self.n_tokens:
            raise IndexError(i)
        value = 0
        for level, (chunk, bitmap, _) in enumerate(self.levels):
            value |= int(chunk[i]) << (level * self.bits)
            if not bitmap[i // 8] >> (i % 8) & 1:
                break
            i = self.rank(level, i)
        return value

    def slice(self, a: int, b: int) -> np.ndarray:
        """Ids a to b: the ids of a run that continue are a run one level up."""
        out = np.zeros(b - a, np.uint32)
        where = np.arange(b - a)
        for level, (chunk, bitmap, _) in enumerate(self.levels):
            out[where] |= chunk[a:b].astype(np.uint32) << np.uint32(level * self.bits)
            more = np.unpackbits(bitmap[a // 8 : -(-b // 8)], bitorder="little")[a % 8 : a % 8 + b - a].astype(bool)
            if not more.any():
                break
            where = where[more]
            a = self.rank(level, a)
            b = a + len(where)
        return out


def crc32(ids: np.ndarray) -> int:
    return zlib.crc32(ids.astype("<u4").tobytes())


# --- files -------------------------------------------------------------------


def write(docs: DataFrame, path: str, vocabulary: str, id_col: str = "doc_id", text: str = "text", end_id: int = 0, bits: int = 8, parts: int | None = None) -> None:
    """Encode every whole text and write the images in ascending id order."""
    spark = docs.sparkSession
    parts = parts or max(int(spark.conf.get("spark.sql.shuffle.partitions")), docs.rdd.getNumPartitions())
    named = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text).alias("text")).withColumn("h", F.xxhash64("text"))
    # Ranges split equal ids by text hash: an id that a third of the rows share fills no single task.
    ordered = named.repartitionByRange(parts, "doc_id", "h").sortWithinPartitions("doc_id", "h", "text").select("doc_id", "text")
    names = ["part", "seq", "start_in_part", "n_tokens", "n_docs", "payload"]

    def run(batches):
        enc = encoder(vocabulary)
        part, seq, start = TaskContext.get().partitionId(), 0, 0
        ids, lengths, kept, size = [], [], [], 0

        def flush():
            nonlocal seq, start, ids, lengths, kept, size
            payload = image(np.array(ids, np.int64), np.r_[0, np.cumsum(np.concatenate(lengths))], np.concatenate(kept), bits)
            row = [[part], [seq], [start], [size], [len(ids)], [payload]]
            seq, start = seq + 1, start + size
            ids, lengths, kept, size = [], [], [], 0
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(row, (pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary()))], names=names)

        for b in batches:
            for piece in slices(b, 1):
                flat, each = with_end(*enc.encode_column(piece.column(1)), end_id)
                ids += [NO_ID if d is None else d for d in piece.column(0).to_pylist()]
                lengths.append(each)
                kept.append(flat)
                size += len(flat)
                if size >= IMAGE_TOKENS:
                    yield flush()
        if ids:
            yield flush()

    images = ordered.mapInArrow(run, "part int, seq long, start_in_part long, n_tokens long, n_docs long, payload binary")
    images.write.mode("overwrite").option("compression", "zstd").parquet(path)


def _placed(spark: SparkSession, path: str) -> DataFrame:
    """Images with the global position of their first id; the part totals are one short row a part."""
    images = spark.read.parquet(path)
    totals = images.groupBy("part").agg(F.sum("n_tokens").alias("total"))
    before = totals.select("part", (F.sum("total").over(Window.orderBy("part")) - F.col("total")).alias("before"))
    return images.join(F.broadcast(before), "part").withColumn("start", F.col("before") + F.col("start_in_part"))


def read(spark: SparkSession, path: str) -> DataFrame:
    """One row a document, in file order: doc_id, start, n_tokens, ids."""
    return _documents(spark, path, "ids array<int>", lambda ids: ids.astype(np.int32).tolist(), pa.list_(pa.int32()))


def digests(spark: SparkSession, path: str) -> DataFrame:
    """One row a document: doc_id, start, n_tokens, ids_crc32, from the ids in the files."""
    return _documents(spark, path, "ids_crc32 long", crc32, pa.int64())


def _documents(spark, path, column, f, kind) -> DataFrame:
    def run(batches):
        for b in batches:
            for start, payload in zip(b.column(0).to_pylist(), b.column(1)):
                im = Image(payload.as_py())
                docs = im.doc_ids.tolist()
                for at in range(0, len(docs), 2048):
                    stop = min(at + 2048, len(docs))
                    o = im.offsets[at : stop + 1]
                    # A run of documents is a run of ids: one access by rank, then cut at the offsets.
                    run_ids = im.slice(int(o[0]), int(o[-1]))
                    base = o - o[0]
                    yield pa.RecordBatch.from_arrays(
                        [
                            pa.array([None if d == NO_ID else d for d in docs[at:stop]], pa.int64()),
                            pa.array(o[:-1] + start),
                            pa.array(np.diff(o)),
                            pa.array([f(run_ids[x:y]) for x, y in zip(base[:-1].tolist(), base[1:].tolist())], kind),
                        ],
                        names=["doc_id", "start", "n_tokens", column.split()[0]],
                    )

    return _placed(spark, path).select("start", "payload").mapInArrow(run, f"doc_id long, start long, n_tokens long, {column}")


def lookup(spark: SparkSession, path: str, positions: DataFrame, position: str = "position") -> DataFrame:
    """Single ids at global positions (column `position`): (position, token).

    Positions meet the images' spans, without their bytes, by a coarse equal key;
    each image then meets its own positions (at most one for each of its tokens).
    """
    placed = _placed(spark, path)
    cell = IMAGE_TOKENS
    spans = placed.select("start", (F.col("start") + F.col("n_tokens")).alias("stop")).withColumn("cell", F.explode(F.sequence(F.floor(F.col("start") / cell), F.floor((F.col("stop") - 1) / cell))))
    asked = positions.select(F.col(position).cast("long").alias("position")).filter("position >= 0").withColumn("cell", F.floor(F.col("position") / cell))
    at = asked.distinct().join(spans, "cell").filter("position >= start and position < stop").groupBy("start").agg(F.collect_list("position").alias("at"))
    met = placed.select("start", "payload").join(at, "start")

    def run(batches):
        for b in batches:
            for start, payload, at in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist()):
                im = Image(payload)
                yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array([im[p - start] for p in at], pa.int32())], names=["position", "token"])

    found = met.mapInArrow(run, "position long, token int")
    return asked.select("position").join(found, "position")


def export(spark: SparkSession, path: str, part: int, seq: int) -> bytes | None:
    """Bytes of one file image, to be stored under any name."""
    row = spark.read.parquet(path).filter((F.col("part") == part) & (F.col("seq") == seq)).select("payload").first()
    return bytes(row[0]) if row else None


def shared_path(spark: SparkSession, name: str) -> str:
    """A new folder beside the checkpoints, which all executors share."""
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
