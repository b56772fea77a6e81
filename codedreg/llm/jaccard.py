"""Exact n-gram Jaccard join as a blocked sparse product of documents by word n-grams.

A link needs 100 * intersection >= PERCENT * union.  The bounds that follow from the sizes decide what is multiplied:

* Of a document with n shingles only n - ceil(t * n) + 1 enter the product, rare ones first (prefix bound): linked
  documents share one of these.  Any fixed order is right; this one puts the hashes that many documents hold last, by
  classes of their frequency, so that shared passages do not make candidates.
* Sizes must lie within t of each other.
* The symmetric difference may not exceed (1 - t) / (1 + t) of both sizes.  A parity bitmap of each set gives a lower
  bound of it, which discards nearly all other pairs before any set is fetched.

Documents of equal sets are one row of the product.  In the column of a shingle, first all documents meet the smallest
id (pairs linear in the column; a frequent column is split into parts whose leaders meet in turn).  The product counts in how many columns a
pair meets; each document's fullest such pair is resolved: the documents of one leader are multiplied with the
leader's row in blocks, which accumulates their overlaps, and those below the bound of the two sizes go.  Then only
pairs of different components remain: those of a column are compared in blocks of BLOCK rows, tested by the bounds
where they meet, and resolved by the same product, so no link between different components is lost, while a group of thousands of
near copies costs a pair a member.

Words are hashed by a random table over byte and place in the word, so no pattern of bytes makes words collide.
A document's set holds the distinct hashes of its 4-word shingles (64 bits); with fewer words, of the whole sequence;
without words or text it is empty and linked with nothing.  Rows without doc_id are returned with their size and no
component; of rows that repeat a doc_id the largest set counts and one row returns.  Extra columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codedreg.llm.common import cut, distinct, lean, mix64, shuffle_width, slices
from codedreg.llm.components import connected_components

PERCENT = 85
WORDS = 4
#: A hash counts as frequent from so many documents on; the table of frequent ones has a fixed size.
FREQUENT = 8
FREQUENT_MAX = 1 << 18
#: Columns beyond this class of frequency (some 4096 documents) are split.
PART_LEVEL = 10
WINDOW = 1_000_000
BLOCK = 2048
SMALL = 256
PAIRS_HELD = 500_000
MASK_BITS = 20
BATCH_BYTES = 1 << 20
#: Longer bitmaps are folded to so many words before a block is compared.
BITMAP_WORDS = 256
#: Pairs of a block of a leader, and entries multiplied at once.
ROWS_TOGETHER, ENTRIES_HELD = 2048, 1 << 20

_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
_SPACE = np.isin(np.arange(256), [32, 9, 10, 11, 12, 13])
#: A random number for each place in a stretch of a word and each byte, from two rounds of mixing; further stretches mix anew.
STRETCH = 64
with np.errstate(over="ignore"):
    _TABLE = mix64(mix64(np.arange(1, 256 * STRETCH + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) + np.uint64(0xD6E8FEB86659FD93))
_STEPS = mix64(np.arange(101, 101 + 16, dtype=np.uint64)) | np.uint64(1)


class Shingler:
    """Sorted distinct shingle hashes of texts, computed on the bytes of many texts at once."""

    def __init__(self, words: int = WORDS):
        self.words = words

    def _together(self, texts: list[bytes]) -> Iterator[np.ndarray]:
        raw = b" ".join(texts)
        b = np.frombuffer(raw.translate(_LOWER), np.uint8)
        letter = ~_SPACE[b]
        edge = np.flatnonzero(np.diff(letter, prepend=False, append=False))
        starts, ends = edge[::2], edge[1::2]
        size = ends - starts
        at = np.flatnonzero(letter)
        place = at - np.repeat(starts, size)
        value = _TABLE[(place % STRETCH) * 256 + b[at]]
        if len(size) and size.max() > STRETCH:
            far = place >= STRETCH
            value[far] = mix64(value[far] + (place[far] // STRETCH).astype(np.uint64) * _STEPS[14])
        sums = np.concatenate([[np.uint64(0)], np.cumsum(value)])
        stop = np.cumsum(size)
        word = mix64(sums[stop] - sums[stop - size] + size.astype(np.uint64)) if len(starts) else np.zeros(0, np.uint64)
        k = self.words
        m = len(word) - k + 1
        shingle = mix64(sum(word[i : i + m] * _STEPS[i] for i in range(k))) if m > 0 else np.zeros(0, np.uint64)
        first = np.concatenate([[0], np.cumsum([len(t) + 1 for t in texts])])
        at = np.searchsorted(starts, first)
        for a, z in zip(at[:-1].tolist(), at[1:].tolist()):
            if z - a >= k:
                yield distinct(shingle[a : z - k + 1])
            elif z > a:
                own = np.uint64(z - a)
                for w in word[a:z]:
                    own = mix64(np.array([own * _STEPS[15] + w]))[0]
                yield np.array([own])
            else:
                yield np.zeros(0, np.uint64)

    def sets(self, column) -> Iterator[np.ndarray]:
        """One array for each text of an Arrow column; null is empty.  Few texts at a time become Python's."""
        sizes = pyarrow.compute.binary_length(column).fill_null(0).to_pylist()
        with np.errstate(over="ignore"):
            for a, z in slices(sizes, BATCH_BYTES):
                yield from self._together([(t.as_py() or "").encode() for t in column.slice(a, z - a)])


def need(n: int, percent: int = PERCENT) -> int:
    """The smallest intersection a link of a set of n can have."""
    return -(-percent * n // 100)


def bitmap(own: np.ndarray) -> bytes:
    """Parity of the set's members in each of at least 2n places."""
    places = 64
    while places < 2 * len(own):
        places *= 2
    bits = np.bincount((own >> np.uint64(8) & np.uint64(places - 1)).astype(np.int64), minlength=places) & 1
    return np.packbits(bits.astype(np.uint8), bitorder="little").tobytes()


def fold(words: np.ndarray, size: int) -> np.ndarray:
    while len(words) > size:
        half = len(words) // 2
        words = words[:half] ^ words[half:]
    return words


def may_link(a: bytes, b: bytes, n_a: int, n_b: int, percent: int = PERCENT) -> bool:
    """False only if the sets' symmetric difference is certainly too large, or their sizes are."""
    if 100 * min(n_a, n_b) < percent * max(n_a, n_b):
        return False
    x, y = np.frombuffer(a, np.uint64), np.frombuffer(b, np.uint64)
    size = min(len(x), len(y))
    least = int(np.bitwise_count(fold(x, size) ^ fold(y, size)).sum())
    return least * (100 + percent) <= (100 - percent) * (n_a + n_b)


def _frequent(docs: DataFrame, words: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes that many documents hold, sorted, with the class of their frequency.

    Tasks count windows of their rows and pass on what repeats there; this orders the product and decides nothing else.
    """

    def run(batches):
        shingler, held, total = Shingler(words), [], 0

        def flush():
            h, c = np.unique(np.concatenate(held), return_counts=True)
            many = c > 1
            return pa.RecordBatch.from_arrays([pa.array(h[many].view(np.int64)), pa.array(c[many])], ["h", "c"])

        for batch in batches:
            for own in shingler.sets(batch.column("text")):
                held.append(own)
                total += len(own)
                if total > WINDOW:
                    yield flush()
                    held, total = [], 0
        if held:
            yield flush()

    counts = docs.select("text").mapInArrow(lean(run), "h long, c long").groupBy("h").agg(F.sum("c").alias("c"))
    top = counts.where(F.col("c") >= FREQUENT).orderBy(F.desc("c"), "h").limit(FREQUENT_MAX).toArrow()
    h = top.column("h").to_numpy().view(np.uint64)
    level = np.log2(top.column("c").to_numpy() / FREQUENT).astype(np.uint8) + 1 if len(h) else np.zeros(0, np.uint8)
    order = np.argsort(h)
    return h[order], level[order]


def _index(docs: DataFrame, words: int, percent: int) -> DataFrame:
    """doc_id, n, sig (digest of the set), prefix (its part of the product), parts (into how many parts each one's column is
    split, a power of two), bits (parity bitmap)."""
    sent = docs.sparkSession.sparkContext.broadcast(_frequent(docs, words))

    def run(batches):
        shingler = Shingler(words)
        common, level = sent.value
        for batch in batches:
            rows = []
            for own in shingler.sets(batch.column("text")):
                n = len(own)
                p = n - need(n, percent) + 1 if n else 0
                prefix, parts = own[:p], np.ones(p, np.int32)
                if n and len(common):
                    at = np.minimum(np.searchsorted(common, own), len(common) - 1)
                    rank = np.where(common[at] == own, level[at], 0).astype(np.int32)
                    first = np.lexsort((own, rank))[:p]
                    prefix, parts = own[first], np.int32(1) << np.maximum(0, rank[first] - PART_LEVEL)
                rows.append((n, xxhash.xxh3_128_digest(own.tobytes()), prefix.view(np.int64), parts, bitmap(own) if n else b""))
            if rows:
                n, sig, prefix, parts, bits = zip(*rows)
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(sig, pa.binary()), pa.array(prefix, pa.list_(pa.int64())), pa.array(parts, pa.list_(pa.int32())), pa.array(bits, pa.binary())],
                    ["doc_id", "n", "sig", "prefix", "parts", "bits"],
                )

    return docs.select("doc_id", "text").mapInArrow(lean(run), "doc_id long, n long, sig binary, prefix array<long>, parts array<int>, bits binary")


def _leaders(entries: DataFrame) -> DataFrame:
    """From (h, part, doc_id, n) sorted by these: each document with the smallest one of its part of the column; the first of a part,
    with no other, as b alone."""

    def run(batches):
        last, lead, lead_n = None, 0, 0
        for batch in batches:
            h, part, doc, n = (batch.column(k).to_numpy(zero_copy_only=False) for k in ("h", "part", "doc_id", "n"))
            if not len(h):
                continue
            new = np.concatenate([[last is None or (h[0], part[0]) != last], (h[1:] != h[:-1]) | (part[1:] != part[:-1])])
            head = np.maximum.accumulate(np.where(new, np.arange(len(h)), -1))
            leads = np.where(head >= 0, doc[np.maximum(head, 0)], lead)
            lead_ns = np.where(head >= 0, n[np.maximum(head, 0)], lead_n)
            # the first row of an unsplit column leads it and is no pair of its own
            out = np.flatnonzero(~new | (part >= 0))
            first = pa.array(new[out])
            yield pa.RecordBatch.from_arrays([pa.array(h[out]), pa.array(leads[out]), pa.array(lead_ns[out]), pa.array(doc[out]), pa.array(n[out]), first], ["h", "a", "n_a", "b", "n_b", "first"])
            last, lead, lead_n = (h[-1], part[-1]), leads[-1], lead_ns[-1]

    return entries.mapInArrow(lean(run), "h long, a long, n_a long, b long, n_b long, first boolean")


def _columns(single: DataFrame) -> DataFrame:
    """h with each of its documents (b) and one that leads it (a); the leaders of a split column's parts follow the smallest."""
    width = shuffle_width(single.sparkSession)
    entries = single.select(F.explode(F.arrays_zip("prefix", "parts")).alias("e"), "doc_id", "n")
    part = F.when(F.col("e.parts") > 1, F.pmod(F.xxhash64("doc_id"), F.col("e.parts")).cast("int")).otherwise(-1)
    entries = entries.select(F.col("e.prefix").alias("h"), part.alias("part"), "doc_id", "n")
    dealt = lambda rows: rows.repartition(width, "h", "part").sortWithinPartitions("h", "part", "doc_id")
    found = cut(_leaders(dealt(entries)))
    firsts = found.where("first").select("h", F.lit(-1).alias("part"), F.col("b").alias("doc_id"), F.col("n_b").alias("n"))
    return found.where("not first").unionByName(_leaders(dealt(firsts))).drop("first")


def _with_bits(pairs: DataFrame, index: DataFrame, percent: int) -> DataFrame:
    """Of pairs (a, b, shared) those that the bounds allow."""
    a = index.select(F.col("doc_id").alias("a"), F.col("bits").alias("bits_a"), F.col("n").alias("n_a"))
    b = index.select(F.col("doc_id").alias("b"), F.col("bits").alias("bits_b"), F.col("n").alias("n_b"))

    def run(batches):
        for batch in batches:
            keep = []
            for i, (x, y, n, m) in enumerate(zip(batch.column("bits_a"), batch.column("bits_b"), batch.column("n_a").to_pylist(), batch.column("n_b").to_pylist())):
                if may_link(x.as_py(), y.as_py(), n, m, percent):
                    keep.append(i)
            yield batch.select(["a", "b", "shared"]).take(pa.array(keep, pa.int64()))

    return pairs.join(a, "a").join(b, "b").select("a", "b", "shared", "bits_a", "bits_b", "n_a", "n_b").mapInArrow(lean(run), "a long, b long, shared long")


def _resolve(pairs: DataFrame, docs: DataFrame, index: DataFrame, words: int, percent: int) -> DataFrame:
    """Of the pairs, the links.  Sets are made anew, for documents that a fixed-size mask of the ids lets through."""
    spark = docs.sparkSession
    place = lambda c: F.pmod(F.xxhash64(c), F.lit(1 << MASK_BITS)).cast("int")
    ends = pairs.select(F.explode(F.array("a", "b")).alias("doc_id"))
    mask = np.zeros(1 << MASK_BITS, bool)
    mask[[r[0] for r in ends.select(place("doc_id")).distinct().collect()]] = True
    sent = spark.sparkContext.broadcast(np.packbits(mask))

    def run(batches):
        shingler, open_ = Shingler(words), np.unpackbits(sent.value).astype(bool)
        for batch in batches:
            own = batch.take(pa.array(np.flatnonzero(open_[batch.column("place").to_numpy(zero_copy_only=False)])))
            blobs = [s.tobytes() for s in shingler.sets(own.column("text"))]
            yield pa.RecordBatch.from_arrays([own.column("doc_id"), pa.array(map(xxhash.xxh3_128_digest, blobs), pa.binary()), pa.array(blobs, pa.binary())], ["doc_id", "sig", "own"])

    named = ends.distinct().join(index.select("doc_id", "sig"), "doc_id")
    sets = docs.select("doc_id", "text", place("doc_id").alias("place")).mapInArrow(lean(run), "doc_id long, sig binary, own binary").join(named, ["doc_id", "sig"], "left_semi")
    sets = cut(sets.dropDuplicates(["doc_id"]).drop("sig"))

    # a leader's row meets the rows of its pairs in blocks; a leader of many pairs stands in several
    fill = pairs.groupBy("a").agg(F.ceil(F.count("*") / ROWS_TOGETHER).cast("int").alias("blocks"))
    placed = pairs.join(fill, "a").withColumn("block", F.pmod(F.xxhash64("b"), F.col("blocks")).cast("int")).select("a", "b", "block")
    rows = placed.join(sets.withColumnRenamed("doc_id", "b"), "b").select("a", "block", "b", "own")
    leads = placed.select("a", "block").distinct().join(sets.withColumnRenamed("doc_id", "a"), "a").select("a", "block", F.lit(None).cast("long").alias("b"), "own")
    dealt = rows.unionByName(leads).repartition(shuffle_width(spark), "a", "block").sortWithinPartitions("a", "block", F.asc_nulls_first("b"))

    def multiply(batches):
        lead = np.zeros(0, np.uint64)
        for batch in batches:
            a, b, own = batch.column("a").to_pylist(), batch.column("b").to_pylist(), batch.column("own")
            at = 0
            while at < len(a):
                if b[at] is None:
                    lead = np.frombuffer(own[at].as_py(), np.uint64)
                    at += 1
                stop = at
                while stop < len(a) and b[stop] is not None:
                    stop += 1
                keep = overlaps_suffice(lead, [np.frombuffer(own[i].as_py(), np.uint64) for i in range(at, stop)], percent)
                yield pa.RecordBatch.from_arrays([pa.array(a[at:stop], pa.int64()).filter(pa.array(keep)), pa.array(b[at:stop], pa.int64()).filter(pa.array(keep))], ["a", "b"])
                at = stop

    return dealt.mapInArrow(lean(multiply), "a long, b long")


def overlaps_suffice(lead: np.ndarray, rows: list[np.ndarray], percent: int = PERCENT) -> np.ndarray:
    """Which rows link with a leader: the product of their incidence with the leader's, in blocks of entries."""
    out = np.zeros(len(rows), bool)
    for a, z in slices([len(r) for r in rows], ENTRIES_HELD):
        n = np.array([len(r) for r in rows[a:z]])
        flat = np.concatenate(rows[a:z])
        hit = lead[np.minimum(np.searchsorted(lead, flat), len(lead) - 1)] == flat
        sums = np.concatenate([[0], np.cumsum(hit)])
        stop = np.cumsum(n)
        both = sums[stop] - sums[stop - n]
        out[a:z] = 100 * both >= percent * (n + len(lead) - both)
    return out


def _crossing(columns: DataFrame, labels: DataFrame, index: DataFrame, percent: int) -> DataFrame:
    """Pairs of one column and different components that the bounds allow, beside those with the smallest id.

    Of columns up to SMALL documents the pairs of fitting sizes meet the bitmaps after the same pairs of other columns
    have become one; larger columns carry the bitmaps along and pass on only what the bounds allow.
    """
    heads = columns.groupBy("h").agg(F.min(F.struct("a", "n_a")).alias("x"), (F.count("*") + 1).alias("size")).where("size > 2").select("h", F.col("x.a").alias("doc_id"), F.col("x.n_a").alias("n"), "size")
    entries = columns.join(heads.select("h"), "h", "left_semi").select("h", F.col("b").alias("doc_id"), F.col("n_b").alias("n")).unionByName(heads.select("h", "doc_id", "n"))
    marked = entries.join(labels.withColumnRenamed("node", "doc_id"), "doc_id", "left").withColumn("component", F.coalesce("component", "doc_id"))
    mixed = marked.groupBy("h").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.count("*").alias("size")).where("low <> high")
    rows = cut(marked.join(mixed.select("h", "size"), "h"))
    width = shuffle_width(columns.sparkSession)

    few = rows.where(F.col("size") <= SMALL).select("h", F.lit(0).alias("i"), F.lit(0).alias("j"), F.lit(0).alias("own"), "doc_id", "component", "n", F.lit(b"").alias("bits"))
    few = few.repartition(width, "h").sortWithinPartitions("h").mapInArrow(lean(_meet(percent, False)), "a long, b long").distinct()

    many = rows.where(F.col("size") > SMALL).withColumn("blocks", F.ceil(F.col("size") / BLOCK).cast("int"))
    many = many.join(index.select("doc_id", "bits"), "doc_id").withColumn("own", F.pmod(F.xxhash64("doc_id"), F.col("blocks")).cast("int"))
    grid = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda i: F.struct(F.least(i, F.col("own")).alias("i"), F.greatest(i, F.col("own")).alias("j")))
    many = many.withColumn("cell", F.explode(grid)).select("h", "cell.i", "cell.j", "own", "doc_id", "component", "n", "bits")
    many = many.repartition(width, "h", "i", "j").sortWithinPartitions("h", "i", "j").mapInArrow(lean(_meet(percent, True)), "a long, b long").distinct()
    return _with_bits(few.withColumn("shared", F.lit(1).cast("long")), index, percent).select("a", "b").unionByName(many)


def cell_pairs(own: np.ndarray, doc: np.ndarray, component: np.ndarray, n: np.ndarray, bits: list[bytes] | None, diagonal: bool, percent: int) -> np.ndarray:
    """Pairs (smaller id first) of the rows of a cell, of different components and fitting sizes, that the bitmaps allow."""
    order = np.argsort(n, kind="stable")
    own, doc, component, n = own[order], doc[order], component[order], n[order]
    stop = np.searchsorted(100 * n, 10_000 * n // percent, side="right")
    folded = None
    if bits is not None:
        words = [fold(np.frombuffer(bits[i], np.uint64), BITMAP_WORDS) for i in order]
        # a row meets larger ones, folded to its own size
        size = np.array([len(w) for w in words])
        folded = {int(m): np.stack([fold(w, int(m)) if len(w) >= m else np.zeros(int(m), np.uint64) for w in words]) for m in np.unique(size)}
    found = []
    for i in range(len(doc) - 1):
        j = np.arange(i + 1, max(i + 1, stop[i]))
        j = j[(component[j] != component[i]) & (diagonal | (own[j] != own[i]))]
        if folded is not None and len(j):
            rows = folded[len(words[i])]
            least = np.bitwise_count(rows[j] ^ rows[i]).sum(1, dtype=np.int64)
            j = j[least * (100 + percent) <= (100 - percent) * (n[i] + n[j])]
        if len(j):
            found.append(np.stack([np.minimum(doc[i], doc[j]), np.maximum(doc[i], doc[j])], 1))
    return np.concatenate(found) if found else np.zeros((0, 2), np.int64)


def _meet(percent: int, bounded: bool):
    """Pairs of the rows of each cell, each once among those a task holds."""

    def out_of(found):
        rows = np.unique(np.concatenate(found), axis=0) if found else np.zeros((0, 2), np.int64)
        return pa.RecordBatch.from_arrays([pa.array(rows[:, 0].copy()), pa.array(rows[:, 1].copy())], ["a", "b"])

    def run(batches):
        rest, found, size = None, [], 0
        names = ["h", "i", "j", "own", "doc_id", "component", "n"]

        def cells(table, last):
            """The complete cells of a table, and what may go on."""
            h, i, j, own, doc, component, n = (table.column(k).to_numpy(zero_copy_only=False) for k in names)
            new = np.flatnonzero(np.concatenate([[True], (h[1:] != h[:-1]) | (i[1:] != i[:-1]) | (j[1:] != j[:-1])]))
            cuts = [*new.tolist(), len(h)]
            for x, y in zip(cuts[:-1], cuts[1:] if last else cuts[1:-1]):
                bits = table.column("bits").slice(x, y - x).to_pylist() if bounded else None
                yield cell_pairs(own[x:y], doc[x:y], component[x:y], n[x:y], bits, bool(i[x] == j[x]), percent)

        for batch in batches:
            table = pa.Table.from_batches([batch])
            table = pa.concat_tables([rest, table]).combine_chunks() if rest is not None else table
            if not table.num_rows:
                continue
            for pairs in cells(table, False):
                found.append(pairs)
                size += len(pairs)
                if size > PAIRS_HELD:
                    yield out_of(found)
                    found, size = [], 0
            h, i, j = (table.column(k).to_numpy(zero_copy_only=False) for k in ("h", "i", "j"))
            same = (h == h[-1]) & (i == i[-1]) & (j == j[-1])
            rest = table.slice(int(np.argmax(same)))
        if rest is not None:
            found.extend(cells(rest, True))
        yield out_of(found)

    return run


def jaccard_links(docs: DataFrame, words: int = WORDS, percent: int = PERCENT) -> tuple[DataFrame, DataFrame]:
    """(members: doc_id, n, rep of its equal sets; links between representatives: a, b)."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    index = cut(_index(docs, words, percent))
    nameless = index.where("doc_id is null").select("doc_id", "n", F.lit(None).cast("long").alias("rep"))
    docs, index = docs.where("doc_id is not null"), index.where("doc_id is not null")
    sizes = index.groupBy("doc_id").agg(F.max(F.struct("n", "sig")).alias("x")).select("doc_id", "x.n", "x.sig")
    reps = sizes.where("n > 0").groupBy("sig").agg(F.min("doc_id").alias("rep"))
    members = cut(sizes.join(reps, "sig", "left").select("doc_id", "n", "sig", F.coalesce("rep", "doc_id").alias("rep")))
    alone = members.where("doc_id = rep and n > 0").select("doc_id", "sig")
    single = cut(index.join(alone, ["doc_id", "sig"], "left_semi").dropDuplicates(["doc_id"]))
    members = members.drop("sig")

    columns = cut(_columns(single))
    fits = F.least("n_a", "n_b") * 100 >= F.greatest("n_a", "n_b") * percent
    stars = cut(_with_bits(columns.where(fits).groupBy("a", "b").agg(F.count("*").alias("shared")), single, percent))

    fullest = stars.groupBy("b").agg(F.min(F.struct(-F.col("shared"), F.col("a").alias("a"))).alias("x"))
    closest = cut(fullest.select("x.a", "b"))
    first = cut(_resolve(closest, docs, single, words, percent))
    labels = cut(connected_components(first))

    node = lambda name: labels.select(F.col("node").alias(name), F.col("component").alias(f"c_{name}"))
    open_stars = stars.join(node("a"), "a", "left").join(node("b"), "b", "left").where("coalesce(c_a, a) <> coalesce(c_b, b)").select("a", "b")
    rest = open_stars.unionByName(_crossing(columns, labels, single, percent)).distinct().join(closest, ["a", "b"], "left_anti")
    second = cut(_resolve(cut(rest), docs, single, words, percent))
    return members.unionByName(nameless), first.unionByName(second)


def jaccard_components(docs: DataFrame, words: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """doc_id, n_shingles, component_id of every row."""
    members, links = jaccard_links(docs, words, percent)
    groups = connected_components(links).withColumnRenamed("node", "rep")
    return members.join(groups, "rep", "left").select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component", "rep").alias("component_id"))


#: The same result by comparing every pair that shares a shingle.
ORACLE = r"""
with recursive w as (
  select doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') as w from documents
), s as (
  select doc_id, case when len(w) = 0 then []::varchar[] when len(w) < 4 then [array_to_string(w, ' ')]
    else list_distinct(list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i + 3], ' '))) end as s from w
), e as (select doc_id, unnest(s) as g from s
), n as (select doc_id, len(s)::bigint as n from s
), p as (select a.doc_id as a, b.doc_id as b, count(*) as shared from e a join e b on a.g = b.g and a.doc_id < b.doc_id group by 1, 2
), l as (
  select a, b from p join n x on x.doc_id = a join n y on y.doc_id = b where 100 * shared >= 85 * (x.n + y.n - shared)
), u as (select a, b from l union all select b, a from l
), r as (select doc_id as a, doc_id as c from n union select u.b, r.c from r join u on u.a = r.a)
select n.doc_id, n.n as n_shingles, min(r.c) as component_id from n join r on r.a = n.doc_id group by 1, 2
"""
