"""Harmonic packing of token sequences.

Class k holds pieces of capacity/(k+1) < length <= capacity/k, and a bin of class k takes exactly k of them.  A
document is cut so that every piece fills its class well: whole stretches of the capacity first; then a rest that
would leave more than SLACK of a bin empty gives off one piece of exactly capacity // (k+1), until what is left fits.
Each worker fills bins from its own rows alone.  Pieces of bins that a worker could not fill meet those of up to FAN
other workers, class by class, and so on in a tree whose groups stay below FAN * k rows; the few pieces left at its
root (under k in each class, a number the capacity bounds) are packed by decreasing length.

Null text is empty and yields its end id alone; an empty table yields no rows; repeated rows are packed once each;
extra columns are not read.  Texts of any length are handled, piece by piece.
"""

from __future__ import annotations

import zlib

import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from codedreg.llm.common import cut
from codedreg.llm.tokens import file_coder

CAPACITY = 2048
SLACK = 0.03
FAN = 64
END_ID = 1
BATCH_ROWS = 20_000

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
OPEN = PIECES + ", k int, part long"


def cut_lengths(n: int, capacity: int = CAPACITY, slack: float = SLACK) -> list[tuple[int, int]]:
    """(length, class) of the pieces of n tokens, in order."""
    out = [(capacity, 1)] * (n // capacity)
    rest = n % capacity
    while rest:
        k = capacity // rest
        if k * rest >= (1 - slack) * capacity:
            out.append((rest, k))
            break
        part = capacity // (k + 1)
        out.append((part, capacity // part))
        rest -= part
    return out


def _pieces(docs: DataFrame, tokenizer: str, pattern: str, capacity: int, slack: float) -> DataFrame:
    """Pieces with the bins this worker filled; sequence_id is null where a bin stayed open."""
    end = END_ID.to_bytes(4, "little")

    def run(batches):
        own, part = file_coder(tokenizer, pattern), TaskContext.get().partitionId()
        waiting: dict[int, list[tuple]] = {}
        rows: list[tuple] = []
        bins = 0

        def batch_of(rows):
            columns = list(zip(*rows))
            return pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in columns[:7]), pa.array(columns[7], pa.int32()), pa.array(columns[8], pa.int64())], OPEN_NAMES)

        for batch in batches:
            coded = own.encode_many(t.as_py() or "" for t in batch.column("text"))
            for doc_id, ids in zip(batch.column("doc_id").to_pylist(), coded):
                ids += end
                n, start = len(ids) // 4, 0
                for length, k in cut_lengths(n, capacity, slack):
                    piece = (doc_id, start, length, zlib.crc32(ids[4 * start : 4 * (start + length)]), n)
                    start += length
                    group = waiting.setdefault(k, [])
                    group.append(piece)
                    if len(group) == k:
                        offset = 0
                        for x in group:
                            rows.append((*x, part << 32 | bins, offset, k, part))
                            offset += x[2]
                        bins += 1
                        group.clear()
                if len(rows) >= BATCH_ROWS:
                    yield batch_of(rows)
                    rows = []
        rows += [(*x, None, None, k, part) for k, group in sorted(waiting.items()) for x in group]
        if rows:
            yield batch_of(rows)

    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), "text").mapInArrow(run, OPEN)


OPEN_NAMES = [x.split()[0] for x in OPEN.split(", ")]


def _fill_class(rest: DataFrame, level: int) -> DataFrame:
    """Number the open pieces of each class within a group of workers; complete bins get an id."""
    group = F.shiftright("part", 6 * level)
    by = Window.partitionBy("k", "g").orderBy("part", "doc_id", "start", "ids_crc32")
    numbered = rest.withColumn("g", group).withColumn("i", F.row_number().over(by) - 1).withColumn("size", F.count("*").over(by.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
    bin_no = F.expr("i div k")
    full = F.expr("(i div k + 1) * k <= size")
    number = F.shiftleft(F.lit(level).cast("long"), 56).bitwiseOR(F.shiftleft(F.col("g"), 20)).bitwiseOR(F.shiftleft(F.col("k").cast("long"), 7)).bitwiseOR(bin_no)
    numbered = numbered.withColumn("b", bin_no).withColumn("sequence_id", F.when(full, number))
    along = Window.partitionBy("k", "g", "b").orderBy("i").rowsBetween(Window.unboundedPreceding, -1)
    return numbered.withColumn("offset", F.when(full, F.coalesce(F.sum("length").over(along), F.lit(0)))).select(*OPEN_NAMES)


def _fill_rest(rest: DataFrame, capacity: int) -> DataFrame:
    """Pack the root's pieces, whose number the capacity bounds, by decreasing length."""

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values(["length", "doc_id", "start"], ascending=[False, True, True], kind="stable")
        used: list[int] = []
        places = []
        for n in frame["length"]:
            at = next((i for i, u in enumerate(used) if u + n <= capacity), len(used))
            if at == len(used):
                used.append(0)
            places.append((1 << 61 | at, used[at]))
            used[at] += n
        return frame.assign(sequence_id=[p[0] for p in places], offset=[p[1] for p in places])[PIECES_NAMES]

    return rest.groupBy(F.lit(0).alias("root")).applyInPandas(lambda frame: run(frame[PIECES_NAMES]), PIECES)


PIECES_NAMES = [x.split()[0] for x in PIECES.split(", ")]


def pack_documents(docs: DataFrame, tokenizer: str, pattern: str, capacity: int = CAPACITY, slack: float = SLACK) -> DataFrame:
    """One row per piece: where it stands in its document and in its sequence."""
    made = cut(_pieces(docs, tokenizer, pattern, capacity, slack))
    done = [made.where("sequence_id is not null").select(PIECES_NAMES)]
    rest = made.where("sequence_id is null")
    top = rest.agg(F.max("part")).first()[0] or 0
    level = 0
    while top >> 6 * level:
        level += 1
        made = cut(_fill_class(rest, level))
        done.append(made.where("sequence_id is not null").select(PIECES_NAMES))
        rest = made.where("sequence_id is null")
    done.append(_fill_rest(rest, capacity))
    out = done[0]
    for x in done[1:]:
        out = out.unionByName(x)
    return out
