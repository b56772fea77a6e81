"""Document fingerprints by content-defined chunking.

A gear hash over the last 32 bytes marks chunk boundaries; a strict mask holds up to the normal chunk size and a loose
one after it, which narrows the spread of sizes.  Boundaries depend on nearby bytes only, so an insertion moves just
the chunks around it.  A fingerprint is the set of chunk digests with their lengths; the likeness of two is the bytes
of the chunks they share over those of the smaller set (containment): 1 for equal sets, two empty ones included, and 0
if just one is empty.

Null text is empty.  Equal texts have equal fingerprints.  In descending doc_id, null ids come last; rows of one
doc_id follow each other by text.  A sole row is its own successor; an empty table gives no rows; extra columns are
not read.
"""

from __future__ import annotations

import base64
import hashlib
from bisect import bisect_left

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codedreg.llm.common import mix64, shuffle_width

MIN_BYTES, NORMAL_BYTES, MAX_BYTES = 16, 48, 192
#: Top bits that must be zero before and after the normal size.
STRICT_BITS, LOOSE_BITS = 7, 4
GEAR = (mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(32)).astype(np.uint32)
#: More buckets than tasks, so that several buckets make each task's load even.
BUCKETS_PER_TASK = 4

RESULT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def boundaries(raw: bytes) -> list[int]:
    """Ends of the chunks."""
    n = len(raw)
    if n <= MIN_BYTES:
        return [n] if n else []
    h = GEAR[np.frombuffer(raw, np.uint8)]
    for shift in (1, 2, 4, 8, 16):
        wide = h.copy()
        wide[shift:] += h[:-shift] << np.uint32(shift)
        h = wide
    loose = np.flatnonzero(h < np.uint32(1 << 32 - LOOSE_BITS))
    strict = loose[h[loose] < np.uint32(1 << 32 - STRICT_BITS)].tolist()
    loose = loose.tolist()
    out, start = [], 0
    while n - start > MIN_BYTES:
        low, normal, high = start + MIN_BYTES, min(start + NORMAL_BYTES, n), min(start + MAX_BYTES, n)
        i = bisect_left(strict, low - 1)
        if i < len(strict) and strict[i] < normal:
            start = strict[i] + 1
        else:
            i = bisect_left(loose, normal - 1)
            start = loose[i] + 1 if i < len(loose) and loose[i] < high else high
        out.append(start)
    if start < n:
        out.append(n)
    return out


def chunk_set(raw: bytes) -> dict[int, int]:
    """Digest to length of each distinct chunk."""
    out, start = {}, 0
    for end in boundaries(raw):
        piece = raw[start:end]
        out[xxhash.xxh3_64_intdigest(piece) >> 16] = end - start
        start = end
    return out


def fingerprint(chunks: dict[int, int]) -> str:
    """Six bytes of digest and two of length for each chunk, by digest, in base64."""
    if not chunks:
        return ""
    packed = np.sort(np.fromiter(chunks.keys(), np.uint64, len(chunks)) << np.uint64(16) | np.fromiter(chunks.values(), np.uint64, len(chunks)))
    return base64.b64encode(packed.astype(">u8").tobytes()).decode()


def parse(text: str) -> dict[int, int]:
    packed = np.frombuffer(base64.b64decode(text), ">u8").tolist()
    return {x >> 16: x & 0xFFFF for x in packed}


def likeness(a: dict[int, int], b: dict[int, int]) -> float:
    if not a or not b:
        return float(not a and not b)
    shared = sum(a[x] for x in a.keys() & b.keys())
    return shared / min(sum(a.values()), sum(b.values()))


def edit(text: str, follower: str) -> str:
    """The last third gives way to as much of the follower's beginning."""
    n = len(text) // 3
    return text[: len(text) - n] + follower[:n]


def with_successor(docs: DataFrame) -> DataFrame:
    """Texts dealt into ranges of doc_id, each range followed by a copy of the row that comes next in descending order.

    Range limits are approximate quantiles of the ids; only those and the first row of each range pass the driver.
    """
    width = shuffle_width(docs.sparkSession)
    lowest = -(1 << 63)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).withColumn("o", F.coalesce("doc_id", F.lit(lowest)))
    many = width * BUCKETS_PER_TASK
    limits = sorted(set(rows.select("o").approxQuantile("o", [i / many for i in range(1, many)], 0.1 / many)))
    bucket = F.lit(0)
    if limits:
        places = F.array(*[F.lit(int(x)) for x in limits])
        bucket = F.size(F.filter(places, lambda x: x < F.col("o")))
    rows = rows.withColumn("bucket", bucket.cast("int"))
    firsts = {r["bucket"]: r["o"] for r in rows.groupBy("bucket").agg(F.max("o").alias("o")).collect()}
    order = sorted(firsts, reverse=True)
    copies = [(firsts[after], before) for before, after in zip(order, [*order[1:], *order[:1]])]
    table = docs.sparkSession.createDataFrame(copies or [(lowest, 0)], "o long, target int")
    own = F.struct(F.col("bucket").alias("g"), F.lit(False).alias("copied"))
    also = F.struct(F.col("target").alias("g"), F.lit(True).alias("copied"))
    dealt = rows.join(F.broadcast(table), "o", "left").withColumn("to", F.explode(F.when(F.col("target").isNull(), F.array(own)).otherwise(F.array(own, also))))
    dealt = dealt.select("doc_id", "text", "o", "to.g", "to.copied").repartition(width, "g")
    return dealt.sortWithinPartitions("g", "copied", F.desc("o"), "text")


def fingerprint_documents(docs: DataFrame) -> DataFrame:
    """Fingerprints of every text and of its edited form, with their likeness and that to the next document."""
    names = [x.split()[0] for x in RESULT.split(", ")]

    def row(now, follower, next_chunks):
        doc_id, text, chunks, mark = now
        edited = edit(text, follower).encode()
        other = chunk_set(edited)
        return (doc_id, len(text), hashlib.sha256(edited).hexdigest(), mark, fingerprint(other), likeness(chunks, other), likeness(chunks, next_chunks))

    def run(batches):
        last = group = None
        for batch in batches:
            rows = []
            for doc_id, text, g, copied in zip(batch.column("doc_id").to_pylist(), batch.column("text"), batch.column("g").to_pylist(), batch.column("copied").to_pylist()):
                if g != group:
                    last, group = None, g
                elif last is None:
                    continue
                text = text.as_py()
                chunks = chunk_set(text.encode())
                if last is not None:
                    rows.append(row(last, text, chunks))
                last = None if copied else (doc_id, text, chunks, fingerprint(chunks))
            if rows:
                kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names)

    return with_successor(docs).select("doc_id", "text", "g", "copied").mapInArrow(run, RESULT)
