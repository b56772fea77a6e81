"""Toxicity by a gapped string kernel on sentences, Nystroem landmarks and a linear support vector machine.

A text becomes letters: lower case, what imitates letters between letters counts as these letters, other signs go, white
space is one mark, and single letters in a row join.  Its sentences end at line feeds and at full stops, question and exclamation marks before
white space; of a sentence over LONGEST symbols, windows of that many that overlap by half count, so that every letter
does.  The kernel of two sentences sums, over all triples of symbols that both hold in order, DECAY to the power of the
spans they take in either, for spans of at most SPAN; it is divided by a function of either length (the norm of a
sentence of that length without repeated triples).  Gaps, inserted characters and spaces thus lower a likeness without
breaking it.

Labelled sentences train the machine; a sentence has its text's label.  As only some sentences of a text with the label
can be the reason for it, training goes in rounds (a machine for many instances): the first ranks sentences by the
difference of the classes' mean vectors, and each further one trains on the sentences that the one before ranks highest
in each text, both with and without the label, and on others without it.  Landmarks are drawn from these
sentences; likenesses to them, through the inverse root of the landmarks' own kernel, are a sentence's Nystroem
coordinates, which a squared-hinge machine parts.  As kernel and machine are linear in the triples, the trained machine
is one table of triple weights.  A text's score is a logistic function of its highest margin and of the mean of its
positive margins, fitted on the labelled texts.

The model is fitted on at most SAMPLE_DOCS labelled documents of each class (lowest hashes of ids, the fold 2 left
out) and SENTENCES evenly spaced sentences of each.  Scores cover all rows and whole texts; texts over PIECE characters
are read in pieces, cut at white space if there is any.  Null and empty texts and those without sentences score as a text of margin -1 does;
unlabelled rows are scored alike; without both classes to learn from, the score is the share of label 1 (0 without
labels).  Repeated rows are each scored; extra columns are not read.
"""

from __future__ import annotations

import itertools
import unicodedata

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codedreg.llm.common import crc_fold, cut, distinct, lean, slices
from codedreg.llm.wordtable import spread

SAMPLE_DOCS = 3000
SENTENCES = 80
LANDMARKS, CLEAN_LANDMARKS = 256, 64
ROUNDS = 2
#: Sentences of a text that train the machine: of those with the label this share and at most so many; of those without so many.
TOP_SHARE, TOP, CLEAN_TOP, CLEAN_OTHER = 0.1, 5, 2, 2
DECAY = 0.7
SPAN = 6
LONGEST = 64
THRESHOLD = 0.3
PIECE = 1 << 18
#: Sentences whose vectors the driver holds at once while it trains, and those it compares with landmarks at once.
VECTORS, COMPARED = 1000, 32

RESULT = "doc_id long, held_out boolean, score double, predicted int"

#: Symbols of a subsequence; letters a-z, the mark and four classes of other letters make the symbols, 0 is none.
ORDER = 4
SYMBOLS = 32
KEYS = SYMBOLS**ORDER
MARK = 27
#: Places of a subsequence after its first symbol, and what it weighs.
PLACES = list(itertools.combinations(range(1, SPAN), ORDER - 1))
WEIGHTS = np.array([DECAY ** (p[-1] + 1) for p in PLACES], np.float32)
#: Signs that imitate letters, and the letters.
IMITATES = "01345789@$!|", "oieastegasil"
SPACE, LETTER, IMITATOR, STOP = 1, 2, 4, 8
WIDE = 0x10000


def _kinds() -> tuple[np.ndarray, np.ndarray]:
    """Kind and symbol of each code point; a-z have symbols of their own, other letters share what is left."""
    kind, symbol = np.zeros(WIDE, np.uint8), np.zeros(WIDE, np.uint8)
    for code in range(WIDE):
        char = chr(code)
        if char.isspace():
            kind[code] = SPACE
        elif unicodedata.category(char)[0] == "L":
            kind[code], symbol[code] = LETTER, code - 96 if 97 <= code <= 122 else 28 + code % 4
    for sign, letter in zip(*IMITATES):
        kind[ord(sign)], symbol[ord(sign)] = IMITATOR, ord(letter) - 96
    for mark in ".!?":
        kind[ord(mark)] |= STOP
    return kind, symbol


KIND, SYMBOL = _kinds()


def sentences(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(symbols, start, size, text) of all sentences, SPAN zeros after each."""
    low = [t.lower() for t in texts]
    raw = "\n" + "".join(t + "\n" for t in low)
    code = np.frombuffer(raw.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
    code = np.where(code < WIDE, code, 0x4E00 + code % 5000)
    kind = KIND[code]
    space, letter, sign = kind & SPACE > 0, kind & LETTER > 0, kind & IMITATOR > 0
    stops = code == 10
    stops[1:] |= space[1:] & (kind[:-1] & STOP > 0)
    if sign.any():
        at = np.arange(len(code))
        before = np.maximum.accumulate(np.where(sign, 0, at))
        after = np.minimum.accumulate(np.where(sign, len(code) - 1, at)[::-1])[::-1]
        letter |= sign & letter[before] & letter[after]
    place = np.flatnonzero(letter | space)
    mark, stops = ~letter[place], stops[place]
    # white space of a run is its first character; the first one of all stands before the first text
    lead = mark & np.concatenate([[True], ~mark[:-1]])
    run = np.cumsum(lead)
    ends_here = np.bincount(run[stops], minlength=run[-1] + 1) > 0
    keep = lead | ~mark
    place, run, mark = place[keep], run[keep], mark[keep]
    symbol = np.where(mark, MARK, SYMBOL[code[place]])
    at = np.flatnonzero(mark)
    length = np.diff(at, append=len(mark)) - 1
    single = np.concatenate([[False], (length[:-1] == 1) & (length[1:] == 1)]) & ~ends_here[run[at]]
    whole = np.ones(len(mark), bool)
    whole[at[single]] = False
    symbol, place, run, mark = symbol[whole], place[whole], run[whole], mark[whole]
    edge = np.flatnonzero(mark & ends_here[run])
    start, size = edge[:-1], np.diff(edge) + 1
    some = size > 3
    start, size = start[some], size[some]
    count = np.maximum(1, -(-(size - LONGEST // 2) // (LONGEST // 2)))
    step = spread(np.zeros(len(count), np.int64), count) * (LONGEST // 2)
    first = np.repeat(start, count) + step
    size = np.minimum(LONGEST, np.repeat(size, count) - step)
    borders = np.concatenate([[0], np.cumsum([len(t) + 1 for t in low])])
    owner = np.searchsorted(borders, place[first], side="right") - 1
    laid, starts = lay(symbol[spread(first, size)], size)
    return laid, starts, size, owner


def lay(symbols: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sentences that follow each other, with SPAN zeros after each, and their starts."""
    starts = np.cumsum(size + SPAN) - size - SPAN
    out = np.zeros(int((size + SPAN).sum()) + SPAN, np.int32)
    out[spread(starts, size)] = symbols
    return out, starts


def length_norm(size: np.ndarray) -> np.ndarray:
    squares = sum(np.maximum(size - p[-1], 0) * float(w) * float(w) for p, w in zip(PLACES, WEIGHTS))
    return np.sqrt(np.maximum(squares, 1e-12))


def table_scores(table: np.ndarray, c: np.ndarray, starts: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Inner product of every sentence's subsequences with a table of weights, where those with a zero weigh nothing."""
    if not len(starts):
        return np.zeros(0)
    n = len(c) - SPAN
    total = np.zeros(len(c), np.float32)
    for places, weight in zip(PLACES, WEIGHTS):
        key = c[:n]
        for p in places:
            key = key * SYMBOLS + c[p : p + n]
        total[:n] += weight * table[key]
    return np.add.reduceat(total, starts) / length_norm(size)


def sparse_rows(c: np.ndarray, starts: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(sentence, subsequence, weight): the sentences' vectors."""
    owner = np.repeat(np.arange(len(starts)), np.diff(starts, append=len(c)))
    n = len(c) - SPAN
    owners, keys, weights = [], [], []
    for places, weight in zip(PLACES, WEIGHTS):
        key, there = c[:n], c[:n] > 0
        for p in places:
            key, there = key * SYMBOLS + c[p : p + n], there & (c[p : p + n] > 0)
        keys.append(key[there])
        owners.append(owner[:n][there])
        weights.append(np.full(len(keys[-1]), weight))
    owner, key = np.concatenate(owners), np.concatenate(keys)
    return owner, key, np.concatenate(weights) / length_norm(size)[owner]


class Sample:
    """Sentences of labelled texts, one after the other."""

    def __init__(self, symbols: np.ndarray, size: np.ndarray, text: np.ndarray, label: np.ndarray):
        self.symbols, self.size, self.text, self.label = symbols, size.astype(np.int64), text, label
        self.start = np.cumsum(self.size) - self.size

    def laid(self, chosen: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        size = self.size[chosen]
        return *lay(self.symbols[spread(self.start[chosen], size)], size), size

    def blocks(self, rows: np.ndarray, block: int):
        return (rows[i : i + block] for i in range(0, len(rows), block))

    def margins(self, table: np.ndarray) -> np.ndarray:
        rows = np.arange(len(self.size))
        return np.concatenate([table_scores(table, *self.laid(x)) for x in self.blocks(rows, 5000)]) if len(rows) else np.zeros(0)


def likeness(sample: Sample, rows: np.ndarray, landmarks: np.ndarray, together: int = 64) -> np.ndarray:
    """Kernel values, sentences by landmarks; some landmarks at a time, on the subsequences these hold."""
    own = []
    for part in sample.blocks(landmarks, together):
        owner, key, value = sparse_rows(*sample.laid(part))
        known = distinct(key)
        index = np.full(KEYS, len(known), np.int32)
        index[known] = np.arange(len(known))
        dense = np.zeros((len(known) + 1, len(part)), np.float32)
        np.add.at(dense, (index[key], owner), value.astype(np.float32))
        own.append((index, dense))
    out = np.zeros((len(rows), len(landmarks)), np.float32)
    for i, part in enumerate(sample.blocks(rows, COMPARED)):
        owner, key, value = sparse_rows(*sample.laid(part))
        for j, (index, dense) in enumerate(own):
            at = index[key]
            hit = at < len(dense) - 1
            spread_ = np.bincount(owner[hit] * len(dense) + at[hit], value[hit], len(part) * len(dense)).astype(np.float32)
            out[COMPARED * i : COMPARED * i + len(part), together * j : together * j + dense.shape[1]] = spread_.reshape(len(part), -1) @ dense
    return out


def mean_table(sample: Sample) -> np.ndarray:
    """Difference of the classes' mean vectors, each triple in units of its spread; each text counts alike."""
    total = np.zeros((2, 2, KEYS))
    label = sample.label[sample.text]
    share = 1 / np.bincount(sample.text, minlength=len(sample.label))[sample.text]
    for part in sample.blocks(np.arange(len(sample.size)), VECTORS):
        owner, key, value = sparse_rows(*sample.laid(part))
        weight, own = value * share[part][owner], label[part][owner]
        for y in (0, 1):
            here = own == y
            total[y, 0] += np.bincount(key[here], weight[here], KEYS)
            total[y, 1] += np.bincount(key[here], (weight * value)[here], KEYS)
    for y in (0, 1):
        total[y] /= max(1, len(distinct(sample.text[label == y])))
    return ((total[1, 0] - total[0, 0]) / np.sqrt(total[:, 1].sum(0) + 1e-5)).astype(np.float32)


def train_machine(k: np.ndarray, root: np.ndarray, y: np.ndarray, c: float = 30.0, rounds: int = 50) -> np.ndarray:
    """Squared hinge with a ridge on the coordinates k @ root, by Newton steps on the rows within the margin; the last
    weight is the offset.

    Either class counts as a half, whatever its size.  The coordinates are not laid out: sums over rows are taken of k, in
    blocks, and turned after.
    """
    sign = np.where(y > 0, 1.0, -1.0)
    cost = c / np.where(y > 0, max(1, (y > 0).sum()), max(1, (y <= 0).sum()))
    turn = np.eye(len(root) + 1)
    turn[:-1, :-1] = root
    ridge = np.eye(len(turn)) * 1e-2
    ridge[-1, -1] = 1e-9
    w = np.zeros(len(turn))
    inside = np.ones(len(k), bool)
    for _ in range(rounds):
        left, right = np.zeros(turn.shape), np.zeros(len(turn))
        for a in range(0, len(k), VECTORS):
            some = a + np.flatnonzero(inside[a : a + VECTORS])
            own = np.hstack([k[some], np.ones((len(some), 1))])
            left += own.T @ (own * cost[some, None])
            right += own.T @ (cost[some] * sign[some])
        w = np.linalg.solve(ridge + turn.T @ left @ turn, turn.T @ right)
        inner, margin = root @ w[:-1], np.full(len(k), w[-1])
        for a in range(0, len(k), VECTORS):
            margin[a : a + VECTORS] += k[a : a + VECTORS] @ inner
        new = sign * margin < 1
        if (new == inside).all():
            break
        inside = new
    return w


def fit_curve(features: np.ndarray, y: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """Weights and offset of a logistic function, by damped Newton steps."""
    x = np.hstack([features, np.ones((len(features), 1))])
    w = np.zeros(x.shape[1])
    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        grad = x.T @ (weight * (p - y)) + 1e-3 * w
        hess = x.T @ (x * (weight * p * (1 - p))[:, None]) + 1e-3 * np.eye(len(w))
        step = np.linalg.solve(hess, grad)
        w -= step * min(1.0, 5 / max(1e-9, np.abs(step).max()))
        if np.abs(step).max() < 1e-9:
            break
    return w


def ranked(margin: np.ndarray, text: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sentences by text and falling margin, the place of each within its text, and its text's number of sentences."""
    order = np.lexsort((-margin, text))
    n = np.bincount(text)
    own = text[order]
    first = np.concatenate([[0], np.cumsum(n)[:-1]])
    return order, np.arange(len(order)) - first[own], n[own]


class Model:
    """Triple weights, the machine's offset and the score curve; without weights, the share of label 1."""

    def __init__(self, table: np.ndarray | None, offset: float, curve: np.ndarray | None, prior: float):
        self.table, self.offset, self.curve, self.prior = table, offset, curve, prior

    def margins(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(highest margin, mean positive margin) of each text."""
        parts, owner = [], []
        for i, text in enumerate(texts):
            while len(text) > PIECE:
                at = max(text.rfind(" ", 0, PIECE), text.rfind("\n", 0, PIECE)) + 1 or PIECE
                parts.append(text[:at])
                owner.append(i)
                text = text[at:]
            parts.append(text)
            owner.append(i)
        best, total, count = np.full(len(texts), -1.0), np.zeros(len(texts)), np.zeros(len(texts))
        owner = np.array(owner, np.int64)
        for a, z in slices([len(x) for x in parts], PIECE):
            c, starts, size, text = sentences(parts[a:z])
            own = owner[a:z][text]
            margin = table_scores(self.table, c, starts, size) + self.offset
            np.maximum.at(best, own, margin)
            np.add.at(total, own, np.maximum(margin, 0))
            np.add.at(count, own, 1)
        return best, total / np.maximum(count, 1)

    def features(self, best: np.ndarray, mean: np.ndarray) -> np.ndarray:
        return np.stack([best, np.log1p(100 * mean)], 1)

    def scores(self, texts: list[str]) -> np.ndarray:
        if self.curve is None:
            return np.full(len(texts), self.prior)
        x = self.features(*self.margins(texts))
        return 1 / (1 + np.exp(-np.clip(x @ self.curve[:-1] + self.curve[-1], -30, 30)))


def train(sample: Sample, prior: float) -> Model:
    """The machine of the sample's sentences, in rounds."""
    label = sample.label[sample.text]
    if not (label == 1).any() or not (label == 0).any():
        return Model(None, 0.0, None, prior)
    draw = np.random.default_rng(0)
    table, offset = mean_table(sample), 0.0
    for _ in range(ROUNDS):
        order, place, n = ranked(sample.margins(table), sample.text)
        own = label[order]
        most = np.clip(np.floor(n * TOP_SHARE), 1, TOP)
        with_label = order[(own == 1) & (place < most)]
        first = order[(own == 0) & (place < CLEAN_TOP)]
        others = order[(own == 0) & (place >= CLEAN_TOP)]
        texts_without = max(1, (sample.label == 0).sum())
        without = np.concatenate([first, draw.permutation(others)[: CLEAN_OTHER * texts_without]])
        landmarks = np.concatenate([draw.permutation(with_label)[:LANDMARKS], draw.permutation(without)[:CLEAN_LANDMARKS]])
        value, vector = np.linalg.eigh(likeness(sample, landmarks, landmarks).astype(float))
        root = vector * (1 / np.sqrt(np.maximum(value, 1e-2))) @ vector.T
        rows = np.concatenate([with_label, without])
        w = train_machine(likeness(sample, rows, landmarks), root, label[rows])
        owner, key, triple = sparse_rows(*sample.laid(landmarks))
        table = np.bincount(key, triple * (root @ w[:-1])[owner], KEYS).astype(np.float32)
        offset = float(w[-1])
    return Model(table, offset, None, prior)


def with_curve(model: Model, texts: DataFrame) -> Model:
    """The model with its curve, fitted on whole texts of the sample; each class counts by its share of all labels."""
    sent = texts.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            best, mean = sent.value.margins([t.as_py() or "" for t in batch.column("text")])
            yield pa.RecordBatch.from_arrays([pa.array(best), pa.array(mean), batch.column("toxic")], ["best", "mean", "toxic"])

    rows = texts.mapInArrow(lean(run), "best double, mean double, toxic int").toArrow().sort_by([("best", "ascending"), ("mean", "ascending"), ("toxic", "ascending")])
    best, mean, y = (rows.column(k).to_numpy() for k in ("best", "mean", "toxic"))
    balance = np.where(y > 0, model.prior / (y > 0).mean(), (1 - model.prior) / (y <= 0).mean())
    model.curve = fit_curve(model.features(best, mean), y, balance)
    return model


def sample_ids(marked: DataFrame, size: int) -> DataFrame:
    """doc_id, toxic of at most size documents of each class, those of the lowest hashes of ids."""
    by = F.xxhash64("doc_id")
    return marked.where("toxic = 1").orderBy(by, "doc_id").limit(size).unionByName(marked.where("toxic = 0").orderBy(by, "doc_id").limit(size))


def sample_of(texts: DataFrame, most: int = SENTENCES) -> Sample:
    """The sentences of labelled texts (text, toxic): evenly spaced ones of long texts."""

    def run(batches):
        for batch in batches:
            raw, labels = [t.as_py() or "" for t in batch.column("text")], batch.column("toxic").to_pylist()
            symbols, sizes = [], []
            for a, z in slices([len(t) for t in raw], PIECE):
                c, starts, size, owner = sentences(raw[a:z])
                borders = np.searchsorted(owner, np.arange(z - a + 1))
                for i, j in zip(borders[:-1], borders[1:]):
                    own = np.arange(i, j) if j - i <= most else i + np.arange(most) * (j - i) // most
                    symbols.append(c[spread(starts[own], size[own])].astype(np.uint8).tobytes())
                    sizes.append(size[own].astype(np.uint8).tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(symbols, pa.binary()), pa.array(sizes, pa.binary()), pa.array(labels, pa.int32())], ["symbols", "sizes", "toxic"])

    rows = texts.mapInArrow(lean(run), "symbols binary, sizes binary, toxic int").toArrow()
    rows = rows.sort_by([("symbols", "ascending"), ("toxic", "ascending")])
    sizes = [np.frombuffer(x.as_py(), np.uint8) for x in rows.column("sizes")]
    symbols = np.frombuffer(b"".join(rows.column("symbols").to_pylist()), np.uint8)
    text = np.repeat(np.arange(len(sizes)), [len(x) for x in sizes])
    return Sample(symbols, np.concatenate([np.zeros(0, np.uint8), *sizes]), text, rows.column("toxic").to_numpy())


def fit(docs: DataFrame, labels: DataFrame, sample_docs: int = SAMPLE_DOCS) -> Model:
    """Learn from labelled rows that are not held out."""
    marked = labels.where(F.col("toxic").isNotNull() & (crc_fold(F.col("doc_id")) != 2)).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    marked = marked.withColumn("toxic", (F.col("toxic") > 0).cast("int"))
    shares = {r["toxic"]: r["n"] for r in marked.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    prior = shares.get(1, 0) / max(1, sum(shares.values()))
    if len(shares) < 2:
        return Model(None, 0.0, None, prior)
    chosen = cut(sample_ids(marked, sample_docs))
    texts = cut(docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").select("text", "toxic").distinct())
    model = train(sample_of(texts), prior)
    return with_curve(model, texts) if model.table is not None else model


def score_documents(docs: DataFrame, model: Model, keep: list[str] | None = None) -> DataFrame:
    """doc_id (or the columns to keep, the text travels once) with held_out, score and predicted."""
    doc_id = F.col("doc_id").cast("long").alias("doc_id")
    kept = docs.select(*keep) if keep else docs.select(doc_id)
    names, has_text = kept.columns, "text" in kept.columns
    extra = [] if has_text else [docs["text"].alias("text__")]
    rows = docs.select(*(keep or [doc_id]), F.coalesce(crc_fold(docs["doc_id"]) == 2, F.lit(False)).alias("held_out__"), *extra)
    column = "text" if has_text else "text__"
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        model = sent.value
        for batch in batches:
            texts = batch.column(column)
            lengths = pyarrow.compute.utf8_length(texts).fill_null(0).to_pylist()
            for a, z in slices(lengths, 4 * PIECE):
                part = batch.slice(a, z - a)
                score = model.scores([t.as_py() or "" for t in part.column(column)])
                yield pa.RecordBatch.from_arrays([*(part.column(n) for n in names), part.column("held_out__"), pa.array(score), pa.array((score >= THRESHOLD).astype(np.int32))], [*names, "held_out", "score", "predicted"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema.fields)
    return rows.mapInArrow(lean(run), f"{schema}, held_out boolean, score double, predicted int")
