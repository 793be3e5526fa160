"""Toxicity by weighted finite-state transducers over clauses.

Words become symbols of a small alphabet (insult, threat, target, negation,
report, other). Three transducers read them: one tracks whether a negation
holds, one whether a report is open, one whether a target is near. Their
composition is a single machine whose output names the kind of each match, so
"you are no X" and "they said X" are scored apart from "you X". Insults and
their weights are learned from labels, by whole word and by word beginning, and
a logistic model turns the matched weight of each kind into a score.
"""

from __future__ import annotations

import functools
import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .labels import bounded_sample, residue, training_labels
from .workers import tidy

#: Fixed word lists in the languages of the tables.
NEGATIONS = frozenset("not never no none nicht kein keine nie pas jamais non nunca ningún don't isn't aren't wasn't".split())
REPORTS = frozenset("said says say wrote writes called claimed quoted allegedly sagte schrieb dit écrit dijo escribió".split())
TARGETS = frozenset("you your you're he him she her they them this these those du dich sie ihr dieser tu te vous il elle usted tú él ella".split())
THREATS = frozenset("kill hurt murder stab shoot burn beat destroy strangle töten umbringen tuer frapper matar golpear".split())
INSULTS = frozenset("idiot moron scum trash loser stupid pathetic worthless disgusting clown".split())

#: Bounds of learning: documents of each class, least documents and evidence of an entry.
SAMPLE, LEAST_DOCS, LEAST_ODDS, LEAST_GAIN = 6_000, 3, 1.6, 14.0
BEGINNINGS = (4, 5)
PRIOR_WEIGHT = 2.0
CLAUSE_END = re.compile(r"[.!?;:,\n]+")
WORD = re.compile(r"[^\W\d_]+(?:'[^\W\d_]+)?")

SYMBOLS = ("other", "insult", "threat", "target", "negation", "report")
KINDS = tuple(f"{base}{mark}" for base in ("insult", "threat") for mark in ("", "+target", "-negated", "-reported"))


class Transducer:
    """Deterministic: ``moves[state, symbol] = (next state, output symbol)``; unlisted symbols keep state and pass."""

    def __init__(self, start, moves: dict):
        self.start, self.moves = start, moves

    def step(self, state, symbol):
        return self.moves.get((state, symbol), (state, symbol))

    def compose(self, other: Transducer, alphabet: tuple) -> Transducer:
        """The machine that feeds this one's output to ``other``, over reachable states only."""
        start = (self.start, other.start)
        moves, waiting, seen = {}, [start], {start}
        while waiting:
            state = waiting.pop()
            for symbol in alphabet:
                left, between = self.step(state[0], symbol)
                right, out = other.step(state[1], between)
                moves[state, symbol] = ((left, right), out)
                if (left, right) not in seen:
                    seen.add((left, right))
                    waiting.append((left, right))
        return Transducer(start, moves)


def negation_transducer(scope: int = 3) -> Transducer:
    """Matches within ``scope`` words after a negation leave as negated ones."""
    moves = {}
    for left in range(scope + 1):
        for symbol in SYMBOLS:
            moves[left, symbol] = (max(0, left - 1), symbol)
        moves[left, "negation"] = (scope, "negation")
        if left:
            moves |= {(left, s): (left - 1, f"{s}-negated") for s in ("insult", "threat")}
    return Transducer(0, moves)


def report_transducer(scope: int = 4) -> Transducer:
    """Matches within ``scope`` words after a verb of saying leave as reported ones."""
    symbols = (*SYMBOLS, "insult-negated", "threat-negated")
    moves = {(left, s): (max(0, left - 1), s) for left in range(scope + 1) for s in symbols}
    for left in range(scope + 1):
        moves[left, "report"] = (scope, "report")
        if left:
            moves |= {(left, s): (left - 1, f"{s}-reported") for s in ("insult", "threat")}
    return Transducer(0, moves)


def target_transducer(scope: int = 4) -> Transducer:
    """Matches within ``scope`` words after a target leave as directed ones."""
    symbols = (*SYMBOLS, *(f"{s}-{m}" for s in ("insult", "threat") for m in ("negated", "reported")))
    moves = {(left, s): (max(0, left - 1), s) for left in range(scope + 1) for s in symbols}
    for left in range(scope + 1):
        moves[left, "target"] = (scope, "target")
        if left:
            moves |= {(left, s): (left - 1, f"{s}+target") for s in ("insult", "threat")}
    return Transducer(0, moves)


@functools.cache
def clause_machine() -> Transducer:
    return negation_transducer().compose(report_transducer(), SYMBOLS).compose(target_transducer(), SYMBOLS)


class Grammar:
    """Lexicon and machine; ``features`` sums the weights of a text's matches by kind."""

    def __init__(self, entries: dict[str, float]):
        self.words = {w: v for w, v in entries.items() if not w.endswith("*")}
        self.begins = {w[:-1]: v for w, v in entries.items() if w.endswith("*")}
        self.fixed = INSULTS | THREATS
        for word in self.fixed:
            self.words.setdefault(word, PRIOR_WEIGHT)
        self.quick = frozenset(self.words)
        self.starts = {n: frozenset(b for b in self.begins if len(b) == n) for n in BEGINNINGS}

    def weight(self, word: str) -> float:
        found = self.words.get(word, 0.0)
        if len(word) > BEGINNINGS[-1]:
            for n in BEGINNINGS:
                found = max(found, self.begins.get(word[:n], 0.0))
        return found

    def symbol(self, word: str) -> tuple[str, float]:
        weight = self.weight(word)
        if word in THREATS:
            return "threat", weight
        if weight > 0:
            return "insult", weight
        for name, words in (("negation", NEGATIONS), ("report", REPORTS), ("target", TARGETS)):
            if word in words:
                return name, 0.0
        return "other", 0.0

    def may_match(self, lowered: str) -> bool:
        words = set(WORD.findall(lowered))
        if not self.quick.isdisjoint(words):
            return True
        return any(starts and not starts.isdisjoint([w[:n] for w in words if len(w) > BEGINNINGS[-1]]) for n, starts in self.starts.items())

    def features(self, text: str) -> np.ndarray:
        """Per kind the summed weight, then the heaviest clause and the number of matching clauses; damped by log(1 + x)."""
        lowered = text.lower()
        out = np.zeros(len(KINDS) + 2)
        if not self.may_match(lowered):
            return out
        machine = clause_machine()
        for clause in CLAUSE_END.split(lowered):
            state, total = machine.start, 0.0
            for word in WORD.findall(clause):
                symbol, weight = self.symbol(word)
                state, kind = machine.step(state, symbol)
                if weight > 0:
                    out[KINDS.index(kind)] += weight
                    total += weight
            if total:
                out[-2] = max(out[-2], total)
                out[-1] += 1
        return np.log1p(out)


def with_halves(texts: DataFrame) -> DataFrame:
    """Adds words ``w``, their least three-word shingle ``key``, and the ``half`` to which copies fall together."""
    words = F.filter(F.split(F.lower("body"), r"[^\p{L}']+"), lambda w: F.length(w) >= 3)
    shingle = F.array_min(F.transform(F.sequence(F.lit(0), F.greatest(F.size("w") - 3, F.lit(0))), lambda k: F.xxhash64(F.get("w", k), F.get("w", k + 1), F.get("w", k + 2))))
    return texts.withColumn("w", words).withColumn("key", shingle).withColumn("half", F.pmod("key", F.lit(2)).cast("int"))


def learn_entries(texts: DataFrame) -> tuple[dict[str, float], dict[int, dict[str, float]]]:
    """Entries from ``texts(body, label)`` with halves: words and ``beginning*`` with their log odds, and the same learned without each half.

    Documents that share their least three-word shingle count once, so a group
    of copies is not mistaken for evidence. An entry needs 3 toxic documents,
    log odds of 1.6 and a likelihood-ratio gain of 14.
    """
    rows = texts.where(F.size("w") > 0).groupBy("key", "half", "label").agg(F.max("w").alias("w"))
    sizes = {(r["half"], r["label"]): r["n"] for r in rows.groupBy("half", "label").agg(F.count("*").alias("n")).collect()}
    unique = F.array_distinct("w")
    long_words = F.filter(unique, lambda w: F.length(w) > BEGINNINGS[-1])
    forms = [unique, *[F.transform(long_words, lambda w, n=n: F.concat(F.substring(w, 1, n), F.lit("*"))) for n in BEGINNINGS]]
    entries = rows.select("label", "half", F.explode(F.array_distinct(F.concat(*forms))).alias("entry"))
    counts = entries.groupBy("entry").agg(*[F.count_if((F.col("half") == h) & (F.col("label") == y)).alias(f"n{h}{y}") for h in (0, 1) for y in (0, 1)])
    likely = counts.where(F.col("n01") + F.col("n11") >= LEAST_DOCS)
    share = (sizes.get((0, 1), 0) + sizes.get((1, 1), 0)) / max(1, sum(sizes.values()))
    likely = likely.where((F.col("n01") + F.col("n11")) > 2 * share * (F.col("n00") + F.col("n01") + F.col("n10") + F.col("n11")))
    found = likely.orderBy("entry").collect()  # words of the bounded sample that several of its toxic documents have

    def fitted(halves: tuple[int, ...]) -> dict[str, float]:
        pos, neg = (sum(sizes.get((h, y), 0) for h in halves) for y in (1, 0))
        kept = []
        for r in found:
            p, n = (sum(r[f"n{h}{y}"] for h in halves) for y in (1, 0))
            odds = math.log((p + 0.5) / (pos + 1)) - math.log((n + 0.5) / (neg + 1))
            if p >= LEAST_DOCS and odds >= LEAST_ODDS:
                rate = (p + n) / max(1, pos + neg)
                gain = 2 * (p * math.log(p / (pos * rate)) + (n * math.log(n / (neg * rate)) if n else 0))
                if gain >= LEAST_GAIN:
                    kept.append((odds, r["entry"]))
        return {e: round(o, 6) for o, e in sorted(kept, key=lambda x: (-x[0], x[1]))}

    return fitted((0, 1)), {0: fitted((1,)), 1: fitted((0,))}


def fit_logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray, ridge: float = 1.0, rounds: int = 50) -> np.ndarray:
    """Ridge-penalised logistic coefficients, intercept last and not penalised; Newton steps with halving."""
    a = np.column_stack([x, np.ones(len(x))])
    penalty = np.full(a.shape[1], ridge)
    penalty[-1] = 1e-6
    beta = np.zeros(a.shape[1])

    def loss(b: np.ndarray) -> float:
        z = a @ b
        return float((weight * (np.logaddexp(0, z) - y * z)).sum() + 0.5 * (penalty * b * b).sum())

    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(a @ beta, -40, 40)))
        grad = a.T @ (weight * (p - y)) + penalty * beta
        step = np.linalg.solve((a * (weight * p * (1 - p))[:, None]).T @ a + np.diag(penalty), grad)
        size = 1.0
        while size > 1e-6 and loss(beta - size * step) > loss(beta):
            size /= 2
        beta = beta - size * step
        if np.abs(size * step).max() < 1e-8:
            break
    return beta


class ToxicityModel:
    """Grammar and coefficients; ``score`` is the probability of the label 1."""

    def __init__(self, grammar: Grammar, beta: np.ndarray):
        self.grammar, self.beta = grammar, beta

    def scores(self, texts: pa.Array) -> np.ndarray:
        """Of the texts of a column, one at a time."""
        x = np.array([self.grammar.features(t.as_py() or "") for t in texts]).reshape(len(texts), len(KINDS) + 2)
        return 1 / (1 + np.exp(-np.clip(x @ self.beta[:-1] + self.beta[-1], -40, 40)))


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", sample: int = SAMPLE, held_out: tuple[int, int] = (3, 1)) -> ToxicityModel:
    """Fits on at most ``sample`` documents of each class, held-out ids (crc32 modulo held_out) excluded.

    The lexicon that measures a document while coefficients are fitted was
    learned from the other half of the sample. Without labels of both classes
    only the fixed words count, with a low base score.
    """
    known = training_labels(labels, label_col).where(residue(F.col("doc_id"), held_out[0]) != held_out[1]).persist()
    try:
        totals = {r["label"]: r["n"] for r in known.groupBy("label").agg(F.count("*").alias("n")).collect()}
        chosen = bounded_sample(known, sample)
        bodies = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("body"))
        texts = with_halves(bodies.join(F.broadcast(chosen), "doc_id")).persist()  # 2 x sample ids at most
        entries, others = learn_entries(texts)
        machines = {h: Grammar(e) for h, e in others.items()}

        def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                half, bodies, y = batch.column(0).to_pylist(), batch.column(1), batch.column(2)
                rows = [machines[h].features(bodies[k].as_py()).tolist() for k, h in enumerate(half)]
                yield pa.RecordBatch.from_arrays([y, pa.array(rows, pa.list_(pa.float64()))], ["label", "x"])

        measured = texts.select("half", "body", "label").mapInArrow(tidy(measure), "label int, x array<double>").toPandas()
        texts.unpersist()
    finally:
        known.unpersist()
    if measured["label"].nunique() < 2:
        return ToxicityModel(Grammar(entries), np.array([0.5] * (len(KINDS) + 2) + [-3.0]))
    y = measured["label"].to_numpy(float)
    weight = np.where(y == 1, totals[1] / max(1, (y == 1).sum()), totals[0] / max(1, (y == 0).sum()))
    x = np.stack(measured["x"].to_numpy())
    order = np.lexsort(np.column_stack([x, y]).T)  # rows come in any order
    return ToxicityModel(Grammar(entries), np.round(fit_logistic(x[order], y[order], weight[order] / weight.mean()), 9))


def score_documents(docs: DataFrame, model: ToxicityModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, score)``, one row per input row; null and blank texts get the base score."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(shared.value.scores(batch.column(1)))], ["doc_id", "score"])

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(tidy(run), f"doc_id {kind}, score double")


def keep_clean(docs: DataFrame, model: ToxicityModel, threshold: float = 0.7, text_col: str = "text") -> DataFrame:
    """The rows whose score is under ``threshold``, with all their columns, whatever their names.

    Null and blank texts have the base score, which is low; repeated rows are
    judged one by one and so stay or go together; an empty table stays empty.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(batch.schema.get_field_index(text_col))
            yield batch.filter(pa.array(shared.value.scores(texts) < threshold))

    return docs.mapInArrow(tidy(run), docs.schema)


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with its score and the decision at 0.7."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    scored = score_documents(docs, train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    return scored.select("doc_id", (residue(F.col("doc_id"), 3) == 1).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))
