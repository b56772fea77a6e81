"""Language identification by word-first backoff.

A word the model knows scores each language by its log frequency there.  An unknown word falls back to its character
n-grams, from the longest to single letters: the first length at which any n-gram is known decides, by the mean log
frequency of those known.  A text's languages are ranked by the sums over its words.

The model is fitted on at most SAMPLE_DOCS documents of each language (those with the lowest hashes of their ids) and
keeps the WORDS most frequent words and the GRAMS most frequent n-grams of each length and language, so what is sent to
the workers has a size bound.  Everything else covers all rows.

Texts that are null or hold no letter get `und` and score 0, and so does every text if there is nothing to learn from.
A text none of whose words is known at any length gets the language with most words and an even score.  Ties go to the
language first in alphabetical order.  Repeated rows are each scored; extra columns are not read.
"""

from __future__ import annotations

import re
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from codedreg.llm.common import crc_fold

SAMPLE_DOCS = 2000
WORDS = 20_000
GRAMS = 10_000
LONGEST = 5
SMOOTHING = 0.5
#: Numbers held for the words met, over all languages.
CACHE_NUMBERS = 2_000_000
#: Evidence of at most so many words sharpens a score.
EVIDENCE_WORDS = 20

RESULT = "doc_id long, held_out boolean, lang_pred string, score double"
WORD = re.compile(r"[^\W\d_]+")


def words_of(text: str) -> list[str]:
    return WORD.findall(text.lower())


def grams_of(word: str, n: int) -> list[str]:
    padded = f" {word} "
    return [padded[i : i + n] for i in range(len(padded) - n + 1)]


def sample_ids(labelled: DataFrame, by: str, most: int) -> DataFrame:
    """At most so many rows of each class, those with the lowest hashes; only ids are ranked.

    A threshold from the class's size leaves about twice as many for the ranking, however large the class is.
    """
    sizes = labelled.groupBy(by).agg(F.count("*").alias("n__"))
    hashed = labelled.select("doc_id", by, F.xxhash64("doc_id").alias("h"))
    low = F.pmod(F.col("h"), F.lit(1 << 40)).cast("double") * F.col("n__") <= F.lit((1 << 40) * 2.0 * most + (1 << 44))
    order = Window.partitionBy(by).orderBy(F.pmod(F.col("h"), F.lit(1 << 40)), "h", "doc_id")
    ranked = hashed.join(F.broadcast(sizes), by).where(low).withColumn("i", F.row_number().over(order))
    return ranked.where(F.col("i") <= most).select("doc_id", by)


def count_grams(docs: DataFrame) -> DataFrame:
    """lang, n (0 for words), gram, count over the whole texts given."""

    def run(batches):
        for batch in batches:
            counts: dict[tuple, Counter] = defaultdict(Counter)
            for lang, text in zip(batch.column("lang").to_pylist(), batch.column("text")):
                counts[lang, 0].update(words_of(text.as_py() or ""))
            for lang in {k for k, _ in counts}:
                for word, c in counts[lang, 0].items():
                    for n in range(1, LONGEST + 1):
                        own = counts[lang, n]
                        for g in grams_of(word, n):
                            own[g] += c
            for (lang, n), own in counts.items():
                if own:
                    yield pa.RecordBatch.from_arrays([pa.array([lang] * len(own)), pa.array([n] * len(own), pa.int32()), pa.array(list(own.keys())), pa.array(list(own.values()), pa.int64())], ["lang", "n", "gram", "c"])

    found = docs.select("lang", "text").mapInArrow(run, "lang string, n int, gram string, c long")
    return found.groupBy("lang", "n", "gram").agg(F.sum("c").alias("c"))


class Model:
    """Log frequencies by language of words (length 0) and n-grams."""

    def __init__(self, rows: list[tuple[str, int, str, int]]):
        self.langs = sorted({r[0] for r in rows})
        place = {x: i for i, x in enumerate(self.langs)}
        raw: dict[int, dict[str, np.ndarray]] = defaultdict(dict)
        for lang, n, gram, c in rows:
            raw[n].setdefault(gram, np.zeros(len(place)))[place[lang]] += c
        self.tables: dict[int, dict[str, int]] = {}
        self.rows: dict[int, np.ndarray] = {}
        for n, own in raw.items():
            counts = np.array(list(own.values())) + SMOOTHING
            self.tables[n] = {gram: i for i, gram in enumerate(own)}
            self.rows[n] = np.log(counts / counts.sum(0))
        totals = sum(raw[0].values()) if raw[0] else np.zeros(len(place))
        self.default = int(np.argmax(totals)) if len(place) else 0

    def word(self, word: str) -> np.ndarray | None:
        at = self.tables.get(0, {}).get(word)
        if at is not None:
            return self.rows[0][at]
        padded = f" {word} "
        for n in range(min(LONGEST, len(padded)), 0, -1):
            table = self.tables.get(n)
            if table:
                found = [at for i in range(len(padded) - n + 1) if (at := table.get(padded[i : i + n])) is not None]
                if found:
                    return self.rows[n][found[0]] if len(found) == 1 else self.rows[n][found].sum(0) / len(found)
        return None


class Scorer:
    """A model with a bounded table of the words it has met; row 0 stands for words without evidence."""

    def __init__(self, model: Model):
        self.model = model
        self.most = max(1000, CACHE_NUMBERS // max(1, len(model.langs)))
        self.rows = np.zeros((self.most + 1, len(model.langs)))
        self.places: dict[str, int] = {}
        self.used = 1

    def learn(self, words: set[str]) -> None:
        for w in words:
            vector = self.model.word(w)
            if vector is None:
                self.places[w] = 0
                continue
            if self.used == len(self.rows):
                self.rows = np.vstack([self.rows, np.zeros_like(self.rows)])
            self.rows[self.used] = vector
            self.places[w] = self.used
            self.used += 1

    def text(self, text: str) -> tuple[str, float]:
        model = self.model
        words = words_of(text)
        if not model.langs or not any(map(str.isalpha, words)) and not any(c.isalpha() for w in words for c in w):
            return "und", 0.0
        places = list(map(self.places.get, words))
        if None in places:
            missing = {w for w, p in zip(words, places) if p is None}
            if len(self.places) + len(missing) > self.most:
                self.places, self.used, missing = {}, 1, set(words)
                self.rows = self.rows[: self.most + 1]
            self.learn(missing)
            places = list(map(self.places.__getitem__, words))
        own = np.array(places)
        count = int(np.count_nonzero(own))
        if not count:
            return model.langs[model.default], 1 / len(model.langs)
        total = self.rows[own].sum(0)
        best = int(np.argmax(total))
        sharp = (total - total[best]) * min(1.0, EVIDENCE_WORDS / count)
        return model.langs[best], float(1 / np.exp(sharp).sum())


def fit(docs: DataFrame, sample_docs: int = SAMPLE_DOCS) -> Model:
    """Learn from rows with a language whose id is not held out."""
    labelled = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (crc_fold(F.col("doc_id")) != 2))
    chosen = sample_ids(labelled.select("doc_id", "lang"), "lang", sample_docs)
    texts = docs.select("doc_id", "text").join(F.broadcast(chosen.dropDuplicates(["doc_id"])), "doc_id").select("lang", "text")
    order = Window.partitionBy("lang", "n").orderBy(F.desc("c"), "gram")
    kept = count_grams(texts).withColumn("i", F.row_number().over(order)).where(F.col("i") <= F.when(F.col("n") == 0, WORDS).otherwise(GRAMS))
    return Model([tuple(r) for r in kept.select("lang", "n", "gram", "c").collect()])


def identify(docs: DataFrame, model: Model) -> DataFrame:
    names = [x.split()[0] for x in RESULT.split(", ")]
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        scorer = Scorer(sent.value)
        for batch in batches:
            found = [scorer.text(t.as_py() or "") for t in batch.column("text")]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64())], names)

    held = F.coalesce(crc_fold(F.col("doc_id")) == 2, F.lit(False))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), held.alias("held_out"), "text").mapInArrow(run, RESULT)

