"""Language identification, words first and shorter character strings for unknown words.

A fit counts words and character n-grams (n = 4 to 1, with word ends marked) per language over a bounded sample
of labelled rows. A text is scored by its known words' log frequencies in each language; an unknown word
takes the mean log frequency of its 4-grams, of its 3-grams where none of those is known, and so on.

The one bound is a parameter: ``sample`` labelled rows (chosen by a hash of the id, whole texts). The model holds
every word and n-gram of these, so its size, which is what is collected and broadcast, follows from the sample and not
from the corpus. Predictions cover every row.

Letters are what Unicode's general category L says; number characters and marks end a word.

Defined results: null texts and texts without a letter are ``und`` with score 0; a text of unknown letters only
gets the most frequent language with score 1 / languages; ties go to the language that sorts first; rows with a
null language are predicted but never learned from; without labelled rows everything is ``und``; repeated
rows repeat their results; further columns are not read.
"""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import numbered, require_columns, trimmed

UND = "und"
WORD = re.compile(r"[^\W\d_]+")
LONGEST = 4
ENOUGH = 20  # words from which more evidence no longer sharpens the score


def fold(id_col, folds: int):
    """crc32 of the id as text, modulo folds."""
    return F.pmod(F.crc32(F.coalesce(id_col.cast("string"), F.lit("")).cast("binary")), F.lit(folds))


def words_of(text: str | None) -> list[str]:
    """Runs of letters. The pattern also takes number characters such as superscripts: words with these are split again."""
    out = []
    for word in WORD.findall(text.lower()) if text else ():
        if word.isalpha():
            out.append(word)
        else:
            out += "".join(c if c.isalpha() else " " for c in word).split()
    return out


def grams_of(word: str, n: int) -> list[str]:
    marked = f"^{word}$" if n > 1 else word
    return [marked[i : i + n] for i in range(len(marked) - n + 1)]


def sampled(docs: DataFrame, id_col: str, limit: int) -> DataFrame:
    """About ``limit`` rows at most, chosen by a hash of the id."""
    n = docs.count()
    if n <= limit:
        return docs
    return docs.filter(F.pmod(F.xxhash64(F.col(id_col)), F.lit(1 << 30)) < int((1 << 30) * limit / n))


def _count(batches):
    """(kind, gram, lang, n): kind 0 for words, else the n of the n-gram. Emptied whenever it grows large."""

    def flush(found: Counter):
        rows: Counter = Counter()
        for (lang, word), n in found.items():
            rows[0, word, lang] += n
            for size in range(1, LONGEST + 1):
                for g in grams_of(word, size):
                    rows[size, g, lang] += n
        keys = list(rows)
        for i in range(0, len(keys), 50_000):
            part = keys[i : i + 50_000]
            yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in part], pa.int32()), pa.array([k[1] for k in part]), pa.array([k[2] for k in part]), pa.array([rows[k] for k in part], pa.int64())], ["kind", "gram", "lang", "n"])

    found: Counter = Counter()
    for batch in batches:
        for text, lang in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            for word, n in Counter(words_of(text)).items():
                found[lang, word] += n
            if len(found) > 100_000:
                yield from flush(found)
                found = Counter()
    yield from flush(found)


class Model:
    """Log frequencies of words and n-grams per language, centred so that only differences between languages count."""

    def __init__(self, rows: list[tuple[int, str, str, int]], totals: dict[tuple[int, str], int], cache: int = 200_000):
        self.langs = sorted({lang for _, lang in totals})
        at = {lang: i for i, lang in enumerate(self.langs)}
        sums = np.zeros((LONGEST + 1, max(1, len(self.langs))))
        for (kind, lang), n in totals.items():
            sums[kind, at[lang]] = n
        self.common = self.langs[int(np.argmax(sums[0]))] if self.langs else UND
        places: list[dict[str, int]] = [{} for _ in range(LONGEST + 1)]
        for kind, gram, _, _ in rows:
            places[kind].setdefault(gram, len(places[kind]))
        tables = []
        for kind, place in enumerate(places):
            counts = np.zeros((len(place), max(1, len(self.langs))))
            for k, gram, lang, n in rows:
                if k == kind:
                    counts[place[gram], at[lang]] += n
            logs = np.log((counts + 0.5) / (sums[kind] + 0.5 * max(1, len(place))))
            tables.append((logs - logs.mean(axis=1, keepdims=True)).astype(np.float32))
        self.places, self.tables, self.cache, self.known = places, tables, cache, None

    def reset(self) -> None:
        self.known = dict(self.places[0])
        self.vectors = np.zeros((len(self.known) + 4096, max(1, len(self.langs))))
        self.vectors[: len(self.known)] = self.tables[0]

    def backoff(self, word: str) -> np.ndarray:
        for n in range(LONGEST, 0, -1):
            found = [i for g in grams_of(word, n) if (i := self.places[n].get(g)) is not None]
            if found:
                return self.tables[n][found].mean(axis=0)
        return np.zeros(max(1, len(self.langs)))

    def place(self, word: str) -> int:
        at = self.known.get(word)
        if at is None:
            at = len(self.known)
            if at == len(self.vectors):
                self.vectors = np.concatenate([self.vectors, np.zeros((len(self.vectors) // 2, self.vectors.shape[1]))])
            self.vectors[at] = self.backoff(word)
            self.known[word] = at
        return at

    def predict(self, text: str | None) -> tuple[str, float]:
        words = words_of(text)
        if not words or not self.langs:
            return UND, 0.0
        if self.known is None or len(self.known) > len(self.places[0]) + self.cache:
            self.reset()
        counts = Counter(words)
        rows = [self.place(w) for w in counts]
        weights = np.fromiter(counts.values(), dtype=np.float64, count=len(rows))
        logits = weights @ self.vectors[rows] * (min(len(words), ENOUGH) / len(words))
        if not logits.any():
            return self.common, 1 / len(self.langs)
        odds = np.exp(logits - logits.max())
        best = int(np.argmax(odds))
        return self.langs[best], float(odds[best] / odds.sum())


def fit(docs: DataFrame, sample: int = 3_000, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Model:
    """Learn from the rows of docs with a language."""
    rows = sampled(docs.filter(F.col(lang_col).isNotNull()).select(id_col, text_col, lang_col), id_col, sample).select(text_col, lang_col)
    counted = rows.mapInArrow(trimmed(_count), "kind int, gram string, lang string, n bigint").groupBy("kind", "gram", "lang").agg(F.sum("n").alias("n"))
    table = counted.orderBy("kind", "gram", "lang").toArrow()  # the words and n-grams of the sample
    kept = list(zip(*(table.column(c).to_pylist() for c in ("kind", "gram", "lang", "n"))))
    totals: Counter = Counter()
    for kind, _, lang, n in kept:
        totals[kind, lang] += n
    return Model(kept, dict(totals))


def predict(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, lang_pred, score per row."""
    require_columns(docs, id_col, text_col)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        own = shared.value
        for batch in batches:
            found = [own.predict(t) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64())], [id_col, "lang_pred", "score"])

    return docs.select(id_col, text_col).mapInArrow(trimmed(run), f"`{id_col}` {kind}, lang_pred string, score double")


def language_report(docs: DataFrame, **bounds) -> DataFrame:
    model = fit(docs.filter(fold(F.col("doc_id"), 4) != 2), **bounds)
    return predict(docs, model).select("doc_id", (fold(F.col("doc_id"), 4) == 2).alias("held_out"), "lang_pred", "score")


def keep_identified(docs: DataFrame, floor: float = 0.5, **bounds) -> DataFrame:
    """The rows whose language is found with a score of ``floor`` at least, all columns kept."""
    model = fit(docs.filter(fold(F.col("doc_id"), 4) != 2), **bounds)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    text, plain = docs.columns.index("text"), numbered(docs)

    def run(batches):
        own = shared.value
        for batch in batches:
            found = [own.predict(t) for t in batch.column(text).to_pylist()]
            yield batch.filter(pa.array([lang != UND and score >= floor for lang, score in found], pa.bool_()))

    return plain.mapInArrow(trimmed(run), plain.schema).toDF(*docs.columns)
