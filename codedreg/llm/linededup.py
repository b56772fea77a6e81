"""Fuzzy line deduplication by MinHash.

A line's shingles are the SHINGLE-character substrings of its lower-cased text with white space collapsed (the whole
of it, if shorter).  BANDS bands of ROWS minima each deal the lines into buckets.  Two lines are alike if the exact
Jaccard similarity of their shingles is SIMILAR or more; distributed union-find joins alike lines into components, and
of every component (a line's own copies included) just the first occurrence stays, by (doc_id, line number).

Lines are compared in two rounds.  First, lines that meet in AGREE buckets: all pairs of buckets of up to SMALL lines count, in a
larger one every line's pairs with its NEAR neighbours, so no line is in many pairs.  Then all lines of a larger bucket that still lie in
different components are compared, in blocks of BLOCK: sizes and parity bitmaps discard only pairs that are certainly not alike, the
rest is resolved exactly.  So alike lines that share AGREE small buckets or a larger one always end in one component; for ideal
minima, two lines of the similarity 0.8 share 2 of 14 buckets with a probability of 0.993, and more above (the tests measure at least
0.98 of all pairs).

A line is known by the 64-bit hash of its text.  Bands travel as blocks of bytes, one for each task and bucket; texts
are fetched only for proposed lines, which a mask of fixed size lets through.  Pairs are verified many at once by shingle hashes; a pair within
one shingle of the limit by its shingles.

Lines end at line feeds.  Lines of white space alone stay.  Null text stays null, empty text empty; a document may lose all its lines
and then holds an empty text; documents themselves always stay.  Rows without doc_id stay as they are.  Of rows that
share a doc_id each is a document of its own; rows that repeat both doc_id and text stay alike.  Columns other than
doc_id and text are kept as they are.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codedreg.llm.common import cut, distinct, lean, mix64, shuffle_width, slices
from codedreg.llm.components import connected_components

SHINGLE = 6
BANDS, ROWS = 14, 4
SIMILAR = 0.8
#: Bands that must propose a pair.
AGREE = 2
#: Buckets up to so many lines propose all their pairs; lines of larger ones are paired with so many neighbours.
SMALL, NEAR = 32, 4
BUCKETS_PER_TASK = 4
MASK_BITS = 22
BATCH_CHARS = 1 << 16
WINDOW_LINES = 100_000
HASHES_HELD = 2_000_000
#: Lines and characters of a block of a bucket, and places of all bitmaps of two blocks together.
BLOCK, BLOCK_CHARS = 8192, 8 << 20
PLACES_HELD = 1 << 24

#: Unicode's White_Space.
WHITE = "\t\n\x0b\x0c\r \x85\xa0\u1680\u2000\u2001\u2002\u2003\u2004\u2005\u2006\u2007\u2008\u2009\u200a\u2028\u2029\u202f\u205f\u3000"

_ODD = (mix64(np.arange(7, 7 + BANDS * ROWS, dtype=np.uint64)) >> np.uint64(32)).astype(np.uint32) | np.uint32(1)
_STEPS = mix64(np.arange(1, 1 + SHINGLE // 3, dtype=np.uint64)) | np.uint64(1)


def line_key(line: str) -> int:
    """Signed 64-bit hash of the line as it stands, Spark's xxhash64."""
    return int.from_bytes(xxhash.xxh64_digest(line.encode(), 42), "big", signed=True)


def blank(line: str) -> bool:
    return not line.strip(WHITE)


def normal_line(line: str) -> str:
    line = line.lower()
    # all white space but the plain one counts as not printable, so such lines are normal as they are
    if line.isprintable() and "  " not in line and line[:1] != " " and line[-1:] != " ":
        return line
    return " ".join(line.split())


def window_hashes(text: str) -> np.ndarray:
    """64-bit hashes of all SHINGLE-character substrings: three characters fill one number, a substring is two of these."""
    codes = np.frombuffer(text.encode("utf-32-le"), np.uint32).astype(np.uint64)
    m = len(codes) - SHINGLE + 1
    three = codes[2:] << np.uint64(42)
    three |= codes[1:-1] << np.uint64(21)
    three |= codes[:-2]
    with np.errstate(over="ignore"):
        out = three[:m] * _STEPS[0]
        for i in range(1, SHINGLE // 3):
            out += three[3 * i : 3 * i + m] * _STEPS[i]
        return mix64(out)


def shingles(line: str) -> set[str]:
    line = normal_line(line)
    return {line[i : i + SHINGLE] for i in range(max(1, len(line) - SHINGLE + 1))}


def shingle_hashes(line: str) -> np.ndarray:
    """Distinct 64-bit hashes of the line's shingles, sorted."""
    return distinct(window_hashes(normal_line(line).ljust(SHINGLE, "\0")))


def alike(a: str, b: str) -> bool:
    x, y = shingles(a), shingles(b)
    both = len(x & y)
    return both >= SIMILAR * (len(x) + len(y) - both)


def pairs_alike(x: list[str], y: list[str]) -> np.ndarray:
    """alike of many pairs of lines: counts by hashes, those within one shingle of the limit again by the shingles."""
    out = np.zeros(len(x), bool)
    for a, z in slices([len(p) + len(q) for p, q in zip(x, y)], BATCH_CHARS):
        for i in range(a, z, 1 << 15):
            part = slice(i, min(z, i + (1 << 15)))
            p, q = (_keyed(lines[part]) for lines in (x, y))
            m = part.stop - i
            # both are sorted, so a stable sort merges them
            merged = np.sort(np.concatenate([p, q]), kind="stable")
            both = np.bincount((merged[1:][merged[1:] == merged[:-1]] >> np.uint64(48)).astype(np.int64), minlength=m)
            n = np.bincount((p >> np.uint64(48)).astype(np.int64), minlength=m) + np.bincount((q >> np.uint64(48)).astype(np.int64), minlength=m)
            out[part] = both >= SIMILAR * (n - both)
            for j in np.flatnonzero(np.abs(both - SIMILAR / (1 + SIMILAR) * n) <= 1).tolist():
                out[i + j] = alike(x[i + j], y[i + j])
    return out


def _keyed(lines: list[str]) -> np.ndarray:
    """Sorted distinct numbers of 16 bits for the line and 48 of a shingle's hash."""
    h, size = _hashes([normal_line(x).ljust(SHINGLE, "\0") for x in lines])
    owner = np.repeat(np.arange(len(lines), dtype=np.uint64), size)[: len(h)]
    key = owner << np.uint64(48) | h >> np.uint64(16)
    # substrings that reach into the next line go
    stop = np.cumsum(size)
    inside = np.ones(len(h), bool)
    for i in range(1, SHINGLE):
        inside[stop[:-1] - i] = False
    return distinct(key[inside])


def _hashes(lines: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all substrings of the joined lines, and the lines' sizes."""
    return window_hashes("".join(lines)), np.array([len(x) for x in lines])


def signatures(lines: list[str]) -> np.ndarray:
    """One row of BANDS band hashes for each non-blank line."""
    out = np.empty((len(lines), BANDS), np.uint64)
    with np.errstate(over="ignore"):
        normal = [normal_line(x).ljust(SHINGLE, "\0") for x in lines]
        for a, z in slices([len(x) for x in normal], BATCH_CHARS):
            out[a:z] = _signatures(normal[a:z])
    return out


def _signatures(lines: list[str]) -> np.ndarray:
    h, size = _hashes(lines)
    h = (h >> np.uint64(32)).astype(np.uint32)
    first = np.concatenate([[0], np.cumsum(size)[:-1]])
    # substrings that reach into the next line take the value of the line's last own one
    last = (first + size)[:-1] - SHINGLE
    for i in range(1, SHINGLE):
        h[last + i] = h[last]
    least = np.empty((BANDS * ROWS, len(lines)), np.uint32)
    mixed = np.empty_like(h)
    for k in range(BANDS * ROWS):
        np.multiply(h, _ODD[k], out=mixed)
        np.minimum.reduceat(mixed, first, out=least[k])
    rows = least.reshape(BANDS, ROWS, len(lines))
    bands = np.arange(1, 1 + BANDS, dtype=np.uint64)[:, None]
    for r in range(ROWS):
        bands = mix64(bands ^ rows[:, r])
    return bands.T


def row_hash():
    """Tells rows of one doc_id apart."""
    return F.xxhash64("doc_id", "text")


def _occurrences(docs: DataFrame) -> DataFrame:
    """key, doc_id, row, line of every line that is not blank."""
    # the row's hash is taken before its lines are: after, Spark would take it for each line
    rows = docs.select("doc_id", row_hash().alias("row"), "text")
    lines = rows.select("doc_id", "row", F.posexplode(F.split("text", "\n")).alias("line", "own"))
    return lines.where(F.ltrim("own", F.lit(WHITE)) != "").select(F.xxhash64("own").alias("key"), "doc_id", "row", "line")


def _distinct_lines(batches):
    """Lists of (key, line) new to a window of one task's rows; a line may return in a later window."""
    seen: set[int] = set()
    fresh: list[tuple[int, str]] = []
    for batch in batches:
        for text in batch.column("text"):
            for line in (text.as_py() or "").split("\n"):
                if not blank(line) and (key := line_key(line)) not in seen:
                    seen.add(key)
                    fresh.append((key, line))
        if len(fresh) >= 5000:
            yield fresh
            fresh = []
        if len(seen) > WINDOW_LINES:
            seen.clear()
    if fresh:
        yield fresh


def _proposals(docs: DataFrame) -> DataFrame:
    """Distinct rows: pairs (a, b) of line keys for the first round (member false), and for large buckets the bucket's digest as
    a and each line's key as b (member true)."""
    width = shuffle_width(docs.sparkSession)
    buckets = width * BUCKETS_PER_TASK

    def bands(batches):
        held: list[np.ndarray] = []

        def flush():
            flat = np.concatenate(held)
            bucket = (flat["band"] % np.uint64(buckets)).astype(np.int64)
            order = np.argsort(bucket, kind="stable")
            flat, bucket = flat[order], bucket[order]
            cuts = np.flatnonzero(np.diff(bucket, prepend=-1))
            blobs = [flat[a:z].tobytes() for a, z in zip(cuts, [*cuts[1:], len(flat)])]
            return pa.RecordBatch.from_arrays([pa.array(bucket[cuts], pa.int64()), pa.array(blobs, pa.binary())], ["bucket", "entries"])

        for lines in _distinct_lines(batches):
            sig = signatures([x for _, x in lines])
            entries = np.empty(sig.shape, PAIR)
            entries["band"], entries["key"] = sig, np.array([k for k, _ in lines], np.int64)[:, None]
            held.append(entries.ravel())
            if sum(map(len, held)) > WINDOW_LINES * BANDS:
                yield flush()
                held.clear()
        if held:
            yield flush()

    def meet(batches):
        now, held = None, []
        for batch in batches:
            for bucket, blob in zip(batch.column("bucket").to_pylist(), batch.column("entries")):
                if bucket != now and held:
                    yield pairs_of(held)
                    held = []
                now = bucket
                held.append(np.frombuffer(blob.as_py(), PAIR))
        if held:
            yield pairs_of(held)

    dealt = docs.select("text").mapInArrow(lean(bands), "bucket long, entries binary").repartition(width, "bucket").sortWithinPartitions("bucket")
    found = dealt.mapInArrow(lean(meet), "member boolean, a long, b long, bands long").groupBy("member", "a", "b").agg(F.sum("bands").alias("bands"))
    return found.where(F.col("member") | (F.col("bands") >= AGREE)).drop("bands")


PAIR = np.dtype([("band", np.uint64), ("key", np.int64)])


def pairs_of(held: list[np.ndarray]) -> pa.RecordBatch:
    """All pairs of small buckets; of larger ones every line with the NEAR ones before it by key, and the members.

    The same order in all bands lets most bands propose the same pairs.  Larger buckets name their members under a digest of
    their keys, so equal buckets of several bands become one (and different ones of equal digest are merely compared
    together).
    """
    flat = np.concatenate(held)
    order = np.lexsort((flat["key"], flat["band"]))
    band, key = flat["band"][order], flat["key"][order]
    fresh = np.concatenate([[True], (band[1:] != band[:-1]) | (key[1:] != key[:-1])])
    band, key = band[fresh], key[fresh]
    new = np.concatenate([[True], band[1:] != band[:-1]])
    heads = np.flatnonzero(new)
    sizes = np.diff(heads, append=len(band))
    head, size = np.repeat(heads, sizes), np.repeat(sizes, sizes)
    at = np.arange(len(band))
    pairs = []
    for back in range(1, SMALL):
        x = np.flatnonzero((at - back >= head) & ((size <= SMALL) | (back <= NEAR)))
        pairs.append(np.stack([key[x - back], key[x]], 1))
    both = np.concatenate(pairs)
    both = both[np.lexsort((both[:, 1], both[:, 0]))]
    first = np.flatnonzero(np.concatenate([[True], (both[1:] != both[:-1]).any(1)])) if len(both) else np.zeros(0, np.int64)
    bands = np.diff(first, append=len(both))
    both = both[first]
    with np.errstate(over="ignore"):
        digests = np.add.reduceat(mix64(key.view(np.uint64)), heads)
    inside = size > SMALL
    members = np.stack([np.repeat(digests, sizes)[inside].view(np.int64), key[inside]], 1)
    out = np.concatenate([both, members])
    bands = np.concatenate([bands, np.ones(len(members), np.int64)])
    return pa.RecordBatch.from_arrays([pa.array(np.arange(len(out)) >= len(both)), pa.array(out[:, 0].copy()), pa.array(out[:, 1].copy()), pa.array(bands)], ["member", "a", "b", "bands"])


def _texts(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """key, text of the wanted keys."""
    spark = docs.sparkSession
    mask = np.zeros(1 << MASK_BITS, bool)
    places = wanted.select(F.col("key").bitwiseAND(F.lit((1 << MASK_BITS) - 1)).cast("int")).distinct().toArrow().column(0).to_numpy()
    mask[places] = True
    sent = spark.sparkContext.broadcast(np.packbits(mask))

    def run(batches):
        open_ = np.unpackbits(sent.value).astype(bool)
        for lines in _distinct_lines(batches):
            there = open_[np.array([k for k, _ in lines], np.int64) & ((1 << MASK_BITS) - 1)]
            found = [x for x, keep in zip(lines, there) if keep]
            yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in found], pa.int64()), pa.array([x for _, x in found], pa.string())], ["key", "line"])

    found = docs.select("text").mapInArrow(lean(run), "key long, line string").join(wanted, "key", "left_semi")
    return found.groupBy("key").agg(F.first("line").alias("line"))


class Known:
    """Shingle hashes of lines by key, as long as they fit."""

    def __init__(self):
        self.sets, self.size = {}, 0

    def of(self, key: int, line: str) -> np.ndarray:
        own = self.sets.get(key)
        if own is None:
            if self.size > HASHES_HELD:
                self.sets, self.size = {}, 0
            own = self.sets[key] = shingle_hashes(line)
            self.size += len(own)
        return own


def sets_alike(x: np.ndarray, y: np.ndarray) -> bool:
    if SIMILAR * max(len(x), len(y)) > min(len(x), len(y)):
        return False
    both = len(np.intersect1d(x, y, assume_unique=True))
    return both >= SIMILAR * (len(x) + len(y) - both)


def _bitmaps(sets, n: np.ndarray) -> np.ndarray:
    """One row of parity bits for each set; n are the sets' sizes."""
    places = 64
    while places < 4 * n.max() and 2 * places * len(n) <= PLACES_HELD:
        places *= 2
    out = np.empty((len(n), places // 64), np.uint64)
    for i, own in enumerate(sets):
        bits = np.bincount((own >> np.uint64(8) & np.uint64(places - 1)).astype(np.int64), minlength=places) & 1
        out[i] = np.packbits(bits.astype(np.uint8), bitorder="little").view(np.uint64)
    return out


def crossing_links(rows: list[tuple[int, int, int, str]], diagonal: bool, known: Known) -> list[tuple[int, int]]:
    """Of rows (block, key, component, line), alike pairs that join all components which alike pairs of the rows join.

    Off the diagonal only pairs of different blocks count.
    """
    n = np.array([len(known.of(key, line)) for _, key, _, line in rows])
    order = np.argsort(n, kind="stable")
    rows, n = [rows[i] for i in order], n[order]
    bits = _bitmaps((known.of(key, line) for _, key, _, line in rows), n)
    block = np.array([r[0] for r in rows])
    component = np.unique([r[2] for r in rows], return_inverse=True)[1]
    found = []
    for i in range(len(rows) - 1):
        stop = np.searchsorted(n, n[i] / SIMILAR + 1e-6, side="right")
        open_ = component[i + 1 : stop] != component[i]
        if not diagonal:
            open_ &= block[i + 1 : stop] != block[i]
        at = np.flatnonzero(open_) + i + 1
        if not len(at):
            continue
        least = np.bitwise_count(bits[at] ^ bits[i]).sum(1, dtype=np.int64)
        for j in at[(1 + SIMILAR) * least <= (1 - SIMILAR) * (n[i] + n[at]) + 1e-6].tolist():
            if component[i] != component[j] and sets_alike(known.of(rows[i][1], rows[i][3]), known.of(rows[j][1], rows[j][3])):
                component[component == component[j]] = component[i]
                found.append((rows[i][1], rows[j][1]))
    return found


def _crossing(members: DataFrame, labels: DataFrame, texts: DataFrame) -> DataFrame:
    """Alike pairs (a, b) of one bucket and different components."""
    lengths = texts.select("key", F.length("line").alias("chars")).join(labels.withColumnRenamed("node", "key"), "key", "left")
    marked = members.join(lengths, "key").withColumn("component", F.coalesce("component", "key"))
    mixed = marked.groupBy("bucket").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.greatest(F.count("*") / BLOCK, F.sum("chars") / BLOCK_CHARS).alias("fill")).where("low <> high")
    rows = marked.join(mixed.select("bucket", F.ceil("fill").cast("int").alias("blocks")), "bucket")
    rows = rows.withColumn("own", F.pmod(F.xxhash64("key"), F.col("blocks")).cast("int"))
    grid = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda i: F.struct(F.least(i, F.col("own")).alias("i"), F.greatest(i, F.col("own")).alias("j")))
    rows = rows.join(texts, "key").withColumn("cell", F.explode(grid)).select("bucket", "cell.i", "cell.j", "own", "key", "component", "line")

    def run(batches):
        known, cell, held = Known(), None, []

        def links():
            a, b = zip(*found) if (found := crossing_links(held, cell[1] == cell[2], known)) else ((), ())
            return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

        for batch in batches:
            d = batch.to_pydict()
            for row in zip(*(d[k] for k in ("bucket", "i", "j", "own", "key", "component", "line"))):
                if row[:3] != cell:
                    if held:
                        yield links()
                    cell, held = row[:3], []
                held.append(row[3:])
        if held:
            yield links()

    width = shuffle_width(members.sparkSession)
    return rows.repartition(width, "bucket", "i", "j").sortWithinPartitions("bucket", "i", "j").mapInArrow(lean(run), "a long, b long").distinct()


def line_groups(docs: DataFrame) -> DataFrame:
    """node (a line's key), component of all lines that are alike another one."""
    dealt = cut(_proposals(docs))
    proposed = dealt.where("not member").select("a", "b")
    members = dealt.where("member").select(F.col("a").alias("bucket"), F.col("b").alias("key"))
    wanted = proposed.select(F.explode(F.array("a", "b")).alias("key")).distinct()
    texts = cut(_texts(docs, wanted))

    def compare(batches):
        for batch in batches:
            keep = np.flatnonzero(pairs_alike(batch.column("x").to_pylist(), batch.column("y").to_pylist()))
            yield batch.select(["a", "b"]).take(pa.array(keep))

    a = texts.select(F.col("key").alias("a"), F.col("line").alias("x"))
    b = texts.select(F.col("key").alias("b"), F.col("line").alias("y"))
    labels = cut(connected_components(proposed.join(a, "a").join(b, "b").select("a", "b", "x", "y").mapInArrow(lean(compare), "a long, b long")))
    more = cut(_crossing(members, labels, texts))
    if more.isEmpty():
        return labels
    return connected_components(labels.select(F.col("node").alias("a"), F.col("component").alias("b")).unionByName(more))


def dropped_lines(docs: DataFrame) -> DataFrame:
    """doc_id, row, drop (numbers of the lines that go), for rows that lose any."""
    rows = cut(_occurrences(docs))
    seen = rows.groupBy("key").agg(F.min(F.struct("doc_id", "row", "line")).alias("first"), F.count("*").alias("n"))
    groups = line_groups(docs).withColumnRenamed("node", "key")
    known = seen.join(groups, "key", "left").where("n > 1 or component is not null").withColumn("component", F.coalesce("component", "key"))
    known = cut(known)
    kept = known.groupBy("component").agg(F.min("first").alias("keep"))
    decisions = known.join(kept, "component").select("key", "keep")
    gone = rows.join(decisions, "key").where("struct(doc_id, row, line) <> keep")
    return gone.groupBy("doc_id", "row").agg(F.collect_set("line").alias("drop"))


def dedup_lines(docs: DataFrame) -> DataFrame:
    """The same rows and columns with repeated lines gone from the text."""
    names, schema = docs.columns, docs.schema
    named = docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    drops = dropped_lines(named).select(F.col("doc_id").alias("doc_id__"), F.col("row").alias("row__"), F.col("drop").alias("drop__"))
    own = F.xxhash64(docs["doc_id"].cast("long"), docs["text"])
    # no order is needed, so the texts are not sorted
    joined = docs.join(drops.hint("shuffle_hash"), (docs["doc_id"].cast("long") == drops["doc_id__"]) & (own == drops["row__"]), "left").drop("doc_id__", "row__")

    def run(batches):
        for batch in batches:
            texts = []
            for text, drop in zip(batch.column("text"), batch.column("drop__")):
                if drop.is_valid and text.is_valid:
                    gone = set(drop.as_py())
                    texts.append("\n".join(x for i, x in enumerate(text.as_py().split("\n")) if i not in gone))
                else:
                    texts.append(text.as_py())
            out = batch.select(names)
            yield out.set_column(names.index("text"), "text", pa.array(texts, pa.string()))

    return joined.mapInArrow(lean(run), schema)


def summary(docs: DataFrame) -> DataFrame:
    """doc_id, lines before and after, and the digest of what is left."""
    lines = lambda c: F.when(F.length(c) > 0, F.length(c) - F.length(F.replace(c, F.lit("\n"), F.lit(""))) + 1).otherwise(0).cast("long")
    before = docs.select("doc_id", "text", lines(F.coalesce("text", F.lit(""))).alias("n_lines"))
    after = dedup_lines(before)
    return after.select("doc_id", "n_lines", lines(F.coalesce("text", F.lit(""))).alias("n_left"), F.sha2(F.coalesce("text", F.lit("")).cast("binary"), 256).alias("text_sha256"))
