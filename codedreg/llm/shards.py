"""Token shards in training order.

The documents of an input partition, each followed by END_ID, make one stream of ids, cut into sequences of STRIDE ids
(the partition's last one may be shorter).  Sequence i of n gets the slot that a keyed Feistel network gives: it
permutes the smallest even power of two that holds n, and a value beyond n walks on until it falls inside, which makes
it a permutation of 0..n-1.

Shard s // shard_slots is one binary file; record s % shard_slots of it starts at that number times the record size.
A record holds its slot (8 bytes), its number of ids (4), the ids (2 bytes each, 4 if any id needs them), zeros up to the
stride and a line feed, which Spark's text writer sets.  So a reader seeks any slot by arithmetic and goes on from there, and
the files lie in whatever store Spark reaches.  The manifest comes from the records read back.

The index of a sequence is its place in its input partition plus the counts of earlier partitions; the counts (one
number per partition) are the only thing the driver sees.  The sequences are written to the shared folder first, so a
lost executor cannot shift indices.

Null text is an empty document (its end id alone); an empty table gives no records; repeated rows each have their
place; a null doc_id stays null; extra columns are not read.
"""

from __future__ import annotations

import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from codedreg.llm.common import ensure_checkpoint_dir, shuffle_width, stored
from codedreg.llm.tokens import file_coder

STRIDE = 2048
SHARD_SLOTS = 2048
END_ID = 1
ROUNDS = 6
KEY = 0x5DEECE66D
#: Rounds mix halves of at most this many bits, so products stay within 64-bit integers.
HALF_BITS_MAX = 30
HEADER = 12
BATCH_IDS = 1 << 20
#: Ids are packed for the shuffle and the shared folder.
CODEC = "zstd"

#: Ids of this rank by frequency take one byte of a packed block, others a byte and a part of two.
COMMON = 160

STREAMS = "part long, local long, n_ids long, packed binary, pieces array<struct<doc_id: long, start: long, length: long, place: long>>"


def half_bits(n: int) -> int:
    bits = 1
    while 1 << 2 * bits < n:
        bits += 1
    if bits > HALF_BITS_MAX:
        raise ValueError(f"{n} sequences are more than the permutation covers")
    return bits


def round_keys(key: int, rounds: int = ROUNDS) -> list[int]:
    out, state = [], key & (1 << 62) - 1
    for _ in range(rounds):
        state = (state * 6364136223846793005 + 1442695040888963407) % (1 << 62)
        out.append(state >> 31)
    return out


def permute(i: int, n: int, key: int) -> int:
    """The slot of index i; the plain form of with_slots."""
    bits = half_bits(n)
    mask = (1 << bits) - 1
    while True:
        left, right = i >> bits, i & mask
        for k in round_keys(key):
            mixed = (right + k) % 2147483647 * 48271 % 2147483647
            mixed = (mixed ^ mixed >> 13) * 69621 % 2147483647
            left, right = right, left ^ mixed & mask
        i = left << bits | right
        if i < n:
            return i


def slots_of(index: np.ndarray, n: int, key: int = KEY) -> np.ndarray:
    """permute of each index, by cycle-walking: at most three quarters of the range lie beyond n, so few rounds of walking remain."""
    bits = half_bits(n)
    mask = (1 << bits) - 1
    keys = round_keys(key)
    slot = index.astype(np.int64)
    open_ = np.ones(len(slot), bool)
    while open_.any():
        i = slot[open_]
        left, right = i >> bits, i & mask
        for k in keys:
            mixed = (right + k) % 2147483647 * 48271 % 2147483647
            mixed = (mixed ^ mixed >> 13) * 69621 % 2147483647
            left, right = right, left ^ mixed & mask
        slot[open_] = left << bits | right
        open_ &= slot >= n
    return slot


def pack_ids(ids: np.ndarray) -> bytes:
    """A block of ids: those of two bytes by their rank among the block's, its commonest in one byte; then compressed."""
    if ids.itemsize > 2:
        return pa.compress(ids.tobytes(), CODEC, asbytes=True)
    count = np.bincount(ids, minlength=1 << 16)
    table = np.argsort(-count, kind="stable")[: np.count_nonzero(count)]
    rank = np.zeros(1 << 16, np.int64)
    rank[table] = np.arange(len(table))
    rank = rank[ids]
    rare = rank >= COMMON
    high = np.where(rare, COMMON + (rank - COMMON >> 10), rank).astype(np.uint8)
    low = (rank[rare] - COMMON & 1023).astype("<u2")
    parts = [table.astype("<u2").tobytes(), *(pa.compress(x.tobytes(), CODEC, asbytes=True) for x in (high, low))]
    return np.array([len(table), len(parts[1]), len(low)], "<i8").tobytes() + b"".join(parts)


def unpack_ids(packed: bytes, n: int, width: int) -> np.ndarray:
    if width > 2:
        return np.frombuffer(pa.decompress(packed, width * n, CODEC), f"<u{width}")
    size, middle, rest = np.frombuffer(packed, "<i8", 3).tolist()
    table = np.frombuffer(packed, "<u2", size, 24)
    at = 24 + 2 * size
    rank = np.frombuffer(pa.decompress(packed[at : at + middle], n, CODEC), np.uint8).astype(np.int64)
    rare = rank >= COMMON
    low = np.frombuffer(pa.decompress(packed[at + middle :], 2 * rest, CODEC), "<u2")
    rank[rare] = (rank[rare] - COMMON << 10) + low + COMMON
    return table[rank]


def id_bytes(tokenizer: str, pattern: str) -> int:
    """Bytes of an id in records: 2 if the vocabulary allows, else 4."""
    return 2 if file_coder(tokenizer, pattern).vocabulary_size() <= 1 << 16 else 4


def record_bytes(stride: int, width: int) -> int:
    return HEADER + width * stride + 1


def _streams(docs: DataFrame, tokenizer: str, pattern: str, stride: int, width: int) -> DataFrame:
    """Blocks of whole sequences (the last one of a partition may be short) with the pieces of documents in them."""
    names = ["part", "local", "n_ids", "packed", "pieces"]

    def run(batches):
        own, part, local = file_coder(tokenizer, pattern), TaskContext.get().partitionId(), 0
        end = END_ID.to_bytes(4, "little")
        # ids not yet written, and (doc_id, place of its first id in the document, number of ids) of what they belong to
        ids: list[bytes] = []
        docs: list[tuple] = []
        held = 0

        def flush(last: bool):
            nonlocal ids, docs, held, local
            flat = np.frombuffer(b"".join(ids), "<u4")
            stop = len(flat) if last else len(flat) // stride * stride
            sizes = np.array([n for _, _, n in docs], np.int64)
            first = np.cumsum(sizes) - sizes
            # pieces end where a document or a sequence does
            at = np.unique(np.concatenate([first[first < stop], np.arange(0, stop, stride)]))
            owner = np.searchsorted(first, at, side="right") - 1
            start = np.array([s for _, s, _ in docs], np.int64)[owner] + at - first[owner]
            columns = [pa.array([docs[i][0] for i in owner.tolist()], pa.int64()), pa.array(start), pa.array(np.diff(at, append=stop)), pa.array(at)]
            pieces = pa.StructArray.from_arrays(columns, ["doc_id", "start", "length", "place"])
            blocks = [pa.array([part], pa.int64()), pa.array([local], pa.int64()), pa.array([stop], pa.int64()), pa.array([pack_ids(flat[:stop].astype(f"<u{width}"))], pa.binary())]
            out = pa.RecordBatch.from_arrays([*blocks, pa.ListArray.from_arrays(pa.array([0, len(at)], pa.int32()), pieces)], names)
            local += -(-stop // stride)
            ids, held = [flat[stop:].tobytes()], len(flat) - stop
            docs = [(d, s + max(0, stop - f), n - max(0, stop - f)) for (d, s, n), f in zip(docs, first.tolist()) if f + n > stop]
            return out

        for batch in batches:
            coded = own.encode_many(t.as_py() or "" for t in batch.column("text"))
            for doc_id, own_ids in zip(batch.column("doc_id").to_pylist(), coded):
                ids += [own_ids, end]
                docs.append((doc_id, 0, len(own_ids) // 4 + 1))
                held += len(own_ids) // 4 + 1
                if held > max(BATCH_IDS, stride):
                    yield flush(False)
        if held:
            yield flush(True)

    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), "text").mapInArrow(run, STREAMS)


class Order:
    """The streams of a table, and how many sequences each of their partitions holds."""

    def __init__(self, docs: DataFrame, tokenizer: str, pattern: str, stride: int = STRIDE, key: int = KEY):
        self.stride, self.key, self.width = stride, key, id_bytes(tokenizer, pattern)
        streams = stored(_streams(docs, tokenizer, pattern, stride, self.width))
        counts = streams.groupBy("part").agg(F.max(F.expr(f"local + (n_ids + {stride} - 1) div {stride}")).alias("n")).orderBy("part").collect()
        before, self.total = [], 0
        for part, n in counts:
            before.append((part, self.total))
            self.total += n
        offsets = docs.sparkSession.createDataFrame(before, "part long, before long")
        self.streams = streams.join(F.broadcast(offsets), "part").withColumn("index", F.col("before") + F.col("local")).drop("before")

    def sequences(self) -> DataFrame:
        """slot, n_tokens, ids (compressed) of every sequence."""
        stride, key, width, total = self.stride, self.key, self.width, self.total

        def run(batches):
            for batch in batches:
                for index, n, packed in zip(batch.column("index").to_pylist(), batch.column("n_ids").to_pylist(), batch.column("packed")):
                    ids = unpack_ids(packed.as_py(), n, width)
                    slots = slots_of(np.arange(index, index - (-n // stride)), total, key)
                    parts = [ids[i : i + stride] for i in range(0, n, stride)]
                    blobs = [pa.compress(x.tobytes(), CODEC, asbytes=True) for x in parts]
                    yield pa.RecordBatch.from_arrays([pa.array(slots), pa.array([len(x) for x in parts], pa.int32()), pa.array(blobs, pa.binary())], ["slot", "n_tokens", "ids"])

        return self.streams.select("index", "n_ids", "packed").mapInArrow(run, "slot long, n_tokens int, ids binary")

    def pieces(self) -> DataFrame:
        """doc_id, start, length, slot, offset of every piece of a document."""
        stride, key, total = self.stride, self.key, self.total

        def run(batches):
            for batch in batches:
                yield batch.drop_columns(["index"]).append_column("slot", pa.array(slots_of(batch.column("index").to_numpy(zero_copy_only=False), total, key)))

        rows = self.streams.select("index", F.explode("pieces").alias("piece"))
        place = F.col("piece.place")
        rows = rows.select("piece.doc_id", "piece.start", "piece.length", (place % stride).alias("offset"), (F.col("index") + F.floor(place / stride)).alias("index"))
        return rows.mapInArrow(run, "doc_id long, start long, length long, offset long, slot long")


def record(slot: int, ids: bytes, n_tokens: int, stride: int, width: int) -> bytes:
    """A record without the line feed that ends it."""
    return slot.to_bytes(8, "little") + n_tokens.to_bytes(4, "little") + ids.ljust(width * stride, b"\0")


def write_shards(order: Order, path: str, shard_slots: int = SHARD_SLOTS) -> None:
    """One binary file in each folder shard=N, its records in slot order."""
    stride, width = order.stride, order.width

    def lay(batches):
        for batch in batches:
            slots, n = batch.column("slot").to_pylist(), batch.column("n_tokens").to_pylist()
            records = [record(s, pa.decompress(x.as_buffer(), width * m, CODEC, asbytes=True), m, stride, width) for s, m, x in zip(slots, n, batch.column("ids"))]
            yield pa.RecordBatch.from_arrays([batch.column("slot"), pa.array([s // shard_slots for s in slots], pa.int64()), pa.array(records, pa.binary())], ["slot", "shard", "record"])

    # a shard is written by one task, and a task takes whole shards
    dealt = order.sequences().repartition(shuffle_width(order.streams.sparkSession), F.expr(f"slot div {shard_slots}"))
    laid = dealt.mapInArrow(lay, "slot long, shard long, record binary").sortWithinPartitions("shard", "slot")
    laid.select(F.col("record").cast("string").alias("value"), "shard").write.partitionBy("shard").option("lineSep", "\n").mode("errorifexists").text(path)


def shard_files(spark: SparkSession, path: str) -> dict[int, str]:
    """The file of each shard."""
    jvm = spark.sparkContext._jvm
    folder = jvm.org.apache.hadoop.fs.Path(f"{path}/shard=*/part-*")
    found = folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).globStatus(folder) or []
    names = [x.getPath().toString() for x in found]
    return {int(x.rsplit("/shard=", 1)[1].split("/")[0]): x for x in names}


def parse(raw: bytes, width: int) -> tuple[int, list[int]]:
    """(slot, ids) of a record."""
    n = int.from_bytes(raw[8:HEADER], "little")
    return int.from_bytes(raw[:8], "little"), np.frombuffer(raw, f"<u{width}", n, HEADER).tolist()


def seek_slots(spark: SparkSession, files: dict[int, str], slot: int, count: int, stride: int = STRIDE, shard_slots: int = SHARD_SLOTS, width: int = 2) -> list[tuple[int, list[int]]]:
    """count records from a slot on within its shard, by one seek and one sequential read, for a trainer that resumes."""
    jvm, size = spark.sparkContext._jvm, record_bytes(stride, width)
    place = jvm.org.apache.hadoop.fs.Path(files[slot // shard_slots])
    stream = place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).open(place)
    try:
        stream.seek(slot % shard_slots * size)
        raw = bytes(jvm.org.apache.commons.io.IOUtils.toByteArray(stream, count * size))
    finally:
        stream.close()
    return [parse(raw[i : i + size], width) for i in range(0, len(raw), size)]


def _records(spark: SparkSession, paths: list[str], stride: int, width: int):
    """The records of shard files as bytes; Hadoop's reader splits files at record borders."""
    return spark.sparkContext.binaryRecords(",".join(paths), record_bytes(stride, width))


def read_shards(spark: SparkSession, path: str, start_slot: int = 0, stride: int = STRIDE, shard_slots: int = SHARD_SLOTS, width: int = 2) -> DataFrame:
    """slot, ids from a slot on, for resuming; whole shards before it are not opened."""
    files = [f for s, f in sorted(shard_files(spark, path).items()) if s >= start_slot // shard_slots]
    if not files:
        return spark.createDataFrame([], "slot long, ids array<long>")
    return _records(spark, files, stride, width).map(lambda raw: parse(raw, width)).toDF("slot long, ids array<long>").where(F.col("slot") >= start_slot)


def written_manifest(spark: SparkSession, path: str, order: Order, shard_slots: int = SHARD_SLOTS) -> DataFrame:
    """One row for each piece of a document: where the files hold it, with the checksum of its record as read back."""
    stride, width = order.stride, order.width
    there = spark.createDataFrame([], "slot long, n_tokens int, record_crc32 long")
    if order.total:
        summed = _records(spark, [f"{path}/shard=*/part-*"], stride, width).map(lambda r: (int.from_bytes(r[:8], "little"), int.from_bytes(r[8:HEADER], "little"), zlib.crc32(r)))
        there = summed.toDF("slot long, n_tokens int, record_crc32 long")
    return order.pieces().join(there, "slot").select(
        "doc_id", "start", "length", "slot", "offset", F.expr(f"slot div {shard_slots}").alias("shard"),
        (F.col("slot") % shard_slots * record_bytes(stride, width)).alias("byte_offset"), "n_tokens", "record_crc32",
    )


def materialise(docs: DataFrame, tokenizer: str, pattern: str, stride: int = STRIDE, shard_slots: int = SHARD_SLOTS, path: str | None = None) -> DataFrame:
    """Write the shards, by default to a new folder beside the checkpoints, and return their manifest."""
    spark = docs.sparkSession
    path = path or f"{ensure_checkpoint_dir(spark)}/shards-{uuid.uuid4().hex}"
    order = Order(docs, tokenizer, pattern, stride)
    write_shards(order, path, shard_slots)
    return written_manifest(spark, path, order, shard_slots)
