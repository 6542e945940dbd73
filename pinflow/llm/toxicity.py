"""Toxicity by a weighted finite-state pattern grammar.

Each word is read as a symbol: insult (with a weight), threat, intent, target, negation, reporting verb, clause end
or plain. Five transducers run over the symbols of a clause. The *insult* transducer passes an insult's weight on,
and more of it for further insults of the clause; the *threat* transducer passes a threat's weight on if an
intent opened it, and little otherwise; the *target*, *negation* and *reported speech* transducers rewrite what
is passed on within their scope. Their product is composed once into a single machine, which runs over the clauses that
hold an insult or a threat at all. A text's features are sums over its matched clauses, so a bare word in
a negated or quoted clause counts for less than the same word aimed at somebody.

Insults come from a short fixed list and from words and word stems that labelled rows set apart; the weights
of the features are a logistic fit. Both learn from a bounded sample (``sample`` labelled rows, a hash of the id
chooses), on different folds of it; the lexicon holds whatever of the sample passes, and is all that is broadcast.

Defined results: null and empty texts score what the fit gives a text without matches; rows that repeat an id in
the labels count once, toxic if any says so; null labels are not learned from; without labels of both kinds the
fixed list alone decides; repeated rows repeat their results; further columns are not read.
"""

from __future__ import annotations

import math
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import require_columns
from .langid import fold

TOKEN = re.compile(r"[^\W\d_]+|[.!?;\n]")
PLAIN, INSULT, THREAT, INTENT, TARGET, NEGATION, REPORT, END = range(8)

# Seeds of the grammar's word classes.
INSULTS = "idiot moron stupid trash scum loser worthless pathetic disgusting clown imbecile dumb idiota estúpido basura imbécil dummkopf abschaum idiote stupide ordure".split()
THREATS = "kill hurt destroy beat burn töten vernichten tuer brûler matar quemar".split()
INTENTS = "will shall going gonna must should werde werden wird vais va vamos voy".split()
TARGETS = "you your they them these people he she du ihr sie euch tu vous ils usted ustedes ellos".split()
NEGATIONS = "not never no nor isn aren nicht kein keine nie pas jamais ne nunca jamás".split()
REPORTS = "said says called wrote quoted claimed sagte schrieb dit écrit dijo escribió".split()

STEMS = (4, 5, 6, 7, 8)
FEATURES = 6


class Transducer:
    """States 0..n-1 from 0; step(state, symbol) -> state; passes(state, symbol): what becomes of a weight read in that state."""

    def __init__(self, states: int, step, passes):
        self.states, self.step, self.passes = states, step, passes


def _scope(trigger: int, reach: int):
    """A scope opened by ``trigger`` that lasts ``reach`` further words and ends with the clause."""
    return lambda s, x: reach if x == trigger else 0 if x == END else max(0, s - 1)


def _within(factor: float, outside: float = 1.0, only: int | None = None):
    """``factor`` inside a scope, ``outside`` elsewhere, for the symbol ``only`` or for both kinds of matches."""
    return lambda s, x: 1.0 if only is not None and x != only else factor if s else outside


INSULTING = Transducer(3, lambda s, x: 0 if x == END else min(2, s + (x == INSULT)), lambda s, x: 1.0 + 0.25 * s if x == INSULT else 1.0)
THREATENING = Transducer(6, _scope(INTENT, 5), _within(1.0, 0.2, THREAT))
AIMED = Transducer(5, _scope(TARGET, 4), _within(1.5))
NEGATED = Transducer(4, _scope(NEGATION, 3), _within(0.3))
REPORTED = Transducer(2, lambda s, x: 1 if x == REPORT else 0 if x == END else s, _within(0.5))


def compose(*parts: Transducer) -> tuple[list[list[int]], list[list[float]]]:
    """Product machine as tables: next state and factor, both by (state, symbol). Only reachable states are made."""
    found, queue = {(0,) * len(parts): 0}, [(0,) * len(parts)]
    table: list[list[int]] = []
    for state in queue:
        row = []
        for x in range(END + 1):
            to = tuple(p.step(s, x) for p, s in zip(parts, state))
            if to not in found:
                found[to] = len(found)
                queue.append(to)
            row.append(found[to])
        table.append(row)
    return table, [[math.prod(p.passes(s, x) for p, s in zip(parts, state)) for x in range(END + 1)] for state in queue]


class Grammar:
    """Word classes, composed machine and, once fitted, the coefficients of the features."""

    def __init__(self, words: dict[str, float], stems: dict[str, float], cache: int = 200_000):
        self.words, self.stems, self.limit = words, stems, cache
        self.table, self.factor = compose(INSULTING, THREATENING, AIMED, NEGATED, REPORTED)
        self.coefficients = np.array([-3.0, 0.0, 1.2, 1.0, 0.8, 0.5, 0.0])
        self.fixed = {"\n": (END, 0.0)} | {c: (END, 0.0) for c in ".!?;"}
        for cls, names in ((THREAT, THREATS), (INTENT, INTENTS), (TARGET, TARGETS), (NEGATION, NEGATIONS), (REPORT, REPORTS)):
            self.fixed |= {w: (cls, 1.0) for w in names}
        self.read = dict(self.fixed)

    def symbol(self, token: str) -> tuple[int, float]:
        got = self.read.get(token)
        if got is None:
            weight = self.words.get(token, 0.0)
            for n in STEMS:
                if len(token) > n:
                    weight = max(weight, self.stems.get(token[:n], 0.0))
            got = (INSULT, weight) if weight else (PLAIN, 0.0)
            if len(self.read) > self.limit:
                self.read = dict(self.fixed)
            self.read[token] = got
        return got

    def features(self, text: str | None) -> list[float]:
        tokens = TOKEN.findall(text.lower()) if text else []
        symbol = self.symbol
        read = [symbol(t) for t in tokens]
        hot = [i for i, (x, _) in enumerate(read) if x == INSULT or x == THREAT]
        total = top = strong = aimed = 0.0
        matched = 0
        i = 0
        while i < len(hot):
            first = hot[i]
            while first and read[first - 1][0] != END:
                first -= 1
            state, clause, at = 0, 0.0, first
            while at < len(read) and read[at][0] != END:
                x, weight = read[at]
                if x == INSULT or x == THREAT:
                    factor = self.factor[state][x]
                    clause += weight * factor
                    strong += weight >= 4
                    aimed += factor > 1
                state = self.table[state][x]
                at += 1
            matched += 1
            total, top = total + clause, max(top, clause)
            while i < len(hot) and hot[i] < at:
                i += 1
        return [math.log1p(total), min(top, 12.0), min(strong, 6.0), math.log1p(matched), total / (len(tokens) + 20) * 10, min(aimed, 3.0)]

    def score(self, text: str | None) -> float:
        z = self.coefficients[0] + float(np.dot(self.coefficients[1:], self.features(text)))
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


def lexical(text: str | None) -> set[str]:
    """Distinct words (``word$``) and stems (``^stem``) of a text."""
    out = set()
    for w in set(re.findall(r"[^\W\d_]+", text.lower())) if text else ():
        out.add(w + "$")
        out.update("^" + w[:n] for n in STEMS if len(w) > n)
    return out


def _tally(batches):
    """(entry, toxic documents, clean documents) of the task's rows."""
    bad, good = Counter(), Counter()

    def flush():
        keys = list({**bad, **good})
        for i in range(0, len(keys), 50_000):
            part = keys[i : i + 50_000]
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.string()), pa.array([bad[k] for k in part], pa.int64()), pa.array([good[k] for k in part], pa.int64())], ["entry", "bad", "good"])
        bad.clear()
        good.clear()

    for batch in batches:
        for text, toxic in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            (bad if toxic else good).update(lexical(text))
            if len(bad) + len(good) > 400_000:
                yield from flush()
    yield from flush()


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, rounds: int = 25) -> np.ndarray:
    """Newton steps of a ridge logistic fit; the first coefficient is the constant."""
    x = np.column_stack([np.ones(len(x)), x])
    b = np.zeros(x.shape[1])
    penalty = ridge * np.eye(x.shape[1])
    penalty[0, 0] = 1e-6
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ b, -30, 30)))
        step = np.linalg.solve(x.T @ (x * (p * (1 - p))[:, None]) + penalty, x.T @ (y - p) - penalty @ b)
        b += step
        if np.abs(step).max() < 1e-8:
            break
    return b


def fit(docs: DataFrame, labels: DataFrame, sample: int = 20_000, support: int = 4, least_odds: float = 2.5, id_col: str = "doc_id", text_col: str = "text") -> Grammar:
    known = labels.filter(F.col("toxic").isNotNull() & F.col(id_col).isNotNull()).groupBy(id_col).agg(F.max("toxic").alias("toxic"))
    n = known.count()
    if n > sample:
        known = known.filter(F.pmod(F.xxhash64(F.col(id_col)), F.lit(1 << 30)) < int((1 << 30) * sample / n))
    # About ``sample`` pairs of numbers: small by construction.
    rows = docs.select(id_col, text_col).join(F.broadcast(known), id_col).select(text_col, (F.col("toxic") == 1).alias("toxic"), F.pmod(F.xxhash64(F.col(id_col), F.lit(5)), F.lit(4)).alias("part"))
    tally = rows.filter("part > 0").select(text_col, "toxic").mapInArrow(_tally, "entry string, bad bigint, good bigint").groupBy("entry").agg(F.sum("bad").alias("bad"), F.sum("good").alias("good"))
    sizes = rows.filter("part > 0").agg(F.coalesce(F.sum(F.col("toxic").cast("int")), F.lit(0)).alias("bad"), F.count("*").alias("all")).first()
    bad, good = sizes["bad"], sizes["all"] - sizes["bad"]
    odds = F.log((F.col("bad") + 0.5) / (F.lit(bad + 1.0) - F.col("bad"))) - F.log((F.col("good") + 0.5) / (F.lit(good + 1.0) - F.col("good")))
    found = tally.filter(F.col("bad") >= support).withColumn("odds", odds).filter(F.col("odds") >= least_odds).collect()  # words of the sample
    words, stems = {w: 5.0 for w in INSULTS}, {}
    for r in found:
        if r["entry"][0] == "^":
            stems[r["entry"][1:]] = float(r["odds"])
        else:
            words[r["entry"][:-1]] = max(words.get(r["entry"][:-1], 0.0), float(r["odds"]))
    grammar = Grammar(words, stems)

    def measure(batches):
        for batch in batches:
            x = [grammar.features(t) for t in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.list_(pa.float64())), batch.column(1)], ["x", "toxic"])

    seen = rows.filter("part = 0").select(text_col, "toxic").mapInArrow(measure, "x array<double>, toxic boolean").collect()  # a quarter of sample, FEATURES numbers each
    y = np.array([r["toxic"] for r in seen], dtype=float)
    if 3 <= y.sum() < len(y):
        grammar.coefficients = logistic(np.array([r["x"] for r in seen]), y)
    return grammar


def score(docs: DataFrame, grammar: Grammar, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id and score per row."""
    require_columns(docs, id_col, text_col)
    shared = docs.sparkSession.sparkContext.broadcast(grammar)
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        own = shared.value
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([own.score(t) for t in batch.column(1).to_pylist()], pa.float64())], [id_col, "score"])

    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, score double")


def toxicity_report(docs: DataFrame, labels: DataFrame, **bounds) -> DataFrame:
    held_out = fold(F.col("doc_id"), 5) == 0
    grammar = fit(docs, labels.filter(~held_out), **bounds)
    return score(docs, grammar).select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
