"""Exact top-k inner products by three phases with a uniform threshold.

Each vector is cut into PARTS ranges of components; what a pair scores on one range is a local score.
Phase 1: every task lists, for each query and range, the k highest local scores among its candidates, and resolves the
totals of these.  The k-th highest total found anywhere is a safe cutoff: k candidates reach it.
Phase 2: a candidate that reaches the cutoff must score cutoff / PARTS or more on some range, so every task collects
just those entries.
Phase 3: their totals are resolved exactly, those under the cutoff go, and the k best of each query remain.

Queries meet candidates block by block: blocks of at most about QUERY_ROWS queries and chunks of at most CHUNK_ROWS
candidates are dealt over a grid, and tasks pass on at most k entries a query.  Nothing is broadcast.

Null vectors and vectors holding null or non-finite components take no part.  Vectors of unequal length are compared
on the components that both have.  Ties go to the smaller id.  Rows with the query's own id are not its candidates; of
rows that repeat another id each counts.  Without queries or candidates the result is empty.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from codedreg.llm.common import cut, shuffle_width

PARTS = 2
QUERY_ROWS = 1024
CHUNK_ROWS = 2048
#: Below any score, and its negative is still an integer.
NONE = -(1 << 62)


def integer_vectors(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", scale: int = 64) -> DataFrame:
    """id and floor(scale * x) of each usable vector."""
    usable = F.forall(vector_col, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    floors = F.transform(vector_col, lambda x: F.floor(F.lit(float(scale)) * x.cast("double")))
    return vectors.where(F.col(id_col).isNotNull() & F.col(vector_col).isNotNull() & usable).select(F.col(id_col).cast("long").alias("id"), floors.alias("v"))


def _pack(rows: DataFrame, keys: list[str]) -> DataFrame:
    """Chunks of consecutive rows of one partition and key as blobs; dims are those of the longest vector in the chunk."""
    schema = ", ".join(f"{k} int" for k in keys) + (", " if keys else "") + "ids binary, data binary"
    names = [*keys, "ids", "data"]

    def run(batches):
        held: dict[tuple, list] = {}

        def flush(key):
            rows = held.pop(key)
            width = max(len(v) for _, v in rows)
            data = np.zeros((len(rows), width), np.int64)
            for i, (_, v) in enumerate(rows):
                data[i, : len(v)] = v
            ids = np.array([i for i, _ in rows], np.int64)
            return pa.RecordBatch.from_arrays([*(pa.array([k], pa.int32()) for k in key), pa.array([ids.tobytes()]), pa.array([data.tobytes()])], names)

        for batch in batches:
            columns = [batch.column(k).to_pylist() for k in keys]
            for i, (id_, v) in enumerate(zip(batch.column("id").to_pylist(), batch.column("v"))):
                key = tuple(c[i] for c in columns)
                group = held.setdefault(key, [])
                group.append((id_, np.asarray(v.values)))
                if len(group) == CHUNK_ROWS:
                    yield flush(key)
        for key in list(held):
            yield flush(key)

    return rows.select(*keys, "id", "v").mapInArrow(run, schema)


def _matrix(ids: bytes, data: bytes) -> tuple[np.ndarray, np.ndarray]:
    i = np.frombuffer(ids, np.int64)
    return i, np.frombuffer(data, np.int64).reshape(len(i), -1) if len(i) else np.zeros((0, 0), np.int64)


def _local(q: np.ndarray, c: np.ndarray) -> list[np.ndarray]:
    """Scores on each range of components, as integers; through float64 where that is exact."""
    width = min(q.shape[1], c.shape[1])
    top = width * int(np.abs(q).max(initial=0)) * int(np.abs(c).max(initial=0))
    kind = np.float64 if top < 1 << 53 else np.int64
    bounds = [width * j // PARTS for j in range(PARTS + 1)]
    return [(q[:, a:b].astype(kind) @ c[:, a:b].T.astype(kind)).astype(np.int64) for a, b in zip(bounds, bounds[1:])]


def _best(scores: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Of each row the k highest scores, ties to smaller ids."""
    order = np.lexsort((ids, -scores), axis=1)[:, :k]
    return np.take_along_axis(scores, order, 1), np.take_along_axis(ids, order, 1)


def _listed(local: list[np.ndarray], own: np.ndarray, k: int) -> np.ndarray:
    """Which entries stand on the local list of some range."""
    mask = np.zeros(own.shape, bool)
    for s in local:
        s = np.where(own, NONE, s)
        if s.shape[1] <= k:
            mask[:] = True
        else:
            np.put_along_axis(mask, np.argpartition(s, -k, axis=1)[:, -k:], True, 1)
    return mask & ~own


def _compact(mask: np.ndarray, total: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The k best of the masked entries of each row, in k columns."""
    score = np.where(mask, total, NONE)
    if score.shape[1] > k:
        floor = np.partition(score, -k, axis=1)[:, -k]
        # entries above the k-th score, and of those equal to it the smallest ids: at most 2k columns
        over, tie = score > floor[:, None], (score == floor[:, None]) & mask
        order = np.argsort(ids, kind="stable")
        tie = tie[:, order]
        tie &= np.cumsum(tie, axis=1) <= k
        back = np.empty_like(tie)
        back[:, order] = tie
        keep = (over & mask) | back
        wide = max(1, int(keep.sum(1).max(initial=0)))
        at = np.argsort(~keep, axis=1, kind="stable")[:, :wide]
        score, found = np.where(np.take_along_axis(keep, at, 1), np.take_along_axis(score, at, 1), NONE), ids[at]
    else:
        found = np.broadcast_to(ids, score.shape)
    return _best(score, found, k)


def _task(pairs: DataFrame, k: int, resolve: bool) -> DataFrame:
    """Of each query the k best totals in this task: among listed entries, or among those that pass the threshold."""
    names = ["query_id", "vec_id", "score"]

    def run(batches):
        best: dict[bytes, tuple] = {}
        for batch in batches:
            for i in range(batch.num_rows):
                row = {name: batch.column(name)[i].as_py() for name in batch.schema.names}
                qids, q = _matrix(row["q_ids"], row["q_data"])
                cids, c = _matrix(row["ids"], row["data"])
                local = _local(q, c)
                own = qids[:, None] == cids[None, :]
                total = sum(local)
                if resolve:
                    cutoff = np.frombuffer(row["cutoffs"], np.int64)[:, None]
                    mask = np.zeros(own.shape, bool)
                    for s in local:
                        # s >= cutoff / PARTS in integers; without a cutoff everything passes
                        mask |= (s >= -(-cutoff // PARTS)) | (cutoff == NONE)
                    mask &= ~own & (total >= cutoff)
                else:
                    mask = _listed(local, own, k)
                score, ids = _compact(mask, total, cids, k)
                key = row["q_ids"]
                if key in best:
                    _, s, v = best[key]
                    score, ids = _best(np.hstack([s, score]), np.hstack([v, ids]), k)
                best[key] = (qids, score, ids)
        for qids, score, ids in best.values():
            there = score != NONE
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(qids, there.sum(1))), pa.array(ids[there]), pa.array(score[there])], names)

    return pairs.mapInArrow(run, "query_id long, vec_id long, score long")


def top_k(queries: DataFrame, candidates: DataFrame, k: int = 20) -> DataFrame:
    """query_id, rank, vec_id, score; both inputs as integer_vectors returns them."""
    spark = queries.sparkSession
    width = shuffle_width(spark)
    blocks = max(1, -(-queries.count() // QUERY_ROWS))
    seed = F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")
    query_blocks = cut(_pack(queries.withColumn("b", seed).repartition(blocks, "b"), ["b"]))
    query_blocks = query_blocks.withColumnsRenamed({"ids": "q_ids", "data": "q_data"}).withColumn("block", F.xxhash64("q_ids"))
    spread = F.explode(F.sequence(F.lit(0), F.lit(width - 1))).alias("s")
    chunks = _pack(candidates, []).withColumn("s", F.pmod(F.xxhash64("ids"), F.lit(width)).cast("int"))
    chunks = cut(chunks.select("ids", "data", "s", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("b")))

    listed = _task(query_blocks.select("b", "q_ids", "q_data", spread).join(chunks, ["b", "s"]), k, False)
    ranked = listed.withColumn("i", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score")))).where(F.col("i") <= k)
    cutoffs = ranked.groupBy("query_id").agg(F.when(F.count("*") == k, F.min("score")).alias("cutoff"))

    with_cutoffs = _attach_cutoffs(query_blocks, cutoffs)
    found = _task(with_cutoffs.select("b", "q_ids", "q_data", "cutoffs", spread).join(chunks, ["b", "s"]), k, True)
    last = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", last).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _attach_cutoffs(query_blocks: DataFrame, cutoffs: DataFrame) -> DataFrame:
    """Each query block with its queries' cutoffs, in its own order; without a cutoff, the lowest integer."""
    ids = query_blocks.select("b", "block", "q_ids").mapInArrow(_block_ids, "b int, block long, place long, query_id long")
    cutoff = F.coalesce("cutoff", F.lit(NONE)).alias("cutoff")
    by_block = ids.join(cutoffs, "query_id", "left").groupBy("b", "block").agg(F.sort_array(F.collect_list(F.struct("place", cutoff))).alias("c"))
    packed = by_block.select("b", "block", F.col("c.cutoff").alias("c")).mapInArrow(_pack_cutoffs, "b int, block long, cutoffs binary")
    return query_blocks.join(packed, ["b", "block"])


def _block_ids(batches):
    for batch in batches:
        for b, block, blob in zip(batch.column("b").to_pylist(), batch.column("block").to_pylist(), batch.column("q_ids").to_pylist()):
            ids = np.frombuffer(blob, np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), b, np.int32)), pa.array(np.full(len(ids), block, np.int64)), pa.array(np.arange(len(ids))), pa.array(ids)], ["b", "block", "place", "query_id"])


def _pack_cutoffs(batches):
    for batch in batches:
        blobs = [np.asarray(c.values).astype(np.int64).tobytes() for c in batch.column("c")]
        yield pa.RecordBatch.from_arrays([batch.column("b"), batch.column("block"), pa.array(blobs, pa.binary())], ["b", "block", "cutoffs"])


def queries_of(vectors: DataFrame, every: int) -> DataFrame:
    return vectors.where(F.col("id") % every == 0)


#: The same result by comparing every pair.
ORACLE = """
with v as (
  select vec_id, list_transform(embedding, lambda x: floor(64 * x::double)) as e from embeddings
  where embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0
), s as (
  select q.vec_id as query_id, c.vec_id, list_dot_product(q.e, c.e)::bigint as score
  from v q join v c on q.vec_id <> c.vec_id where q.vec_id % 20 = 0
), r as (
  select *, row_number() over (partition by query_id order by score desc, vec_id) as rank from s
)
select query_id, rank::int as rank, vec_id, score from r where rank <= 20
"""

