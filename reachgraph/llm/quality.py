"""Quality classifier with hierarchical empirical Bayes.

Two logistic models, one for low quality and one for toxicity, are fitted on a
bounded sample of labelled documents; they read which telling words occur and
the shape of the text. What a document says for itself is combined with what
its host and its path on the host are like: grouped sums of the document
evidence give host and path rates, which are shrunk, the sparser the more, to
the level above, with a strength estimated from how much the groups differ.
"""

from __future__ import annotations

import json
import math
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reachgraph.llm.common import bound_batches, small, stored

HEADS = ("low", "toxic")
_MARKS = re.compile(r"[^\w\s.,;:'\"()-]+")
_ENDS = ".,;:!?\"'()[]{}%&$*#@|~_+=<>"
#: Lengths of the beginnings of words that are features beside the words.
PREFIXES = (4, 6)
#: Lower ends of the bins of each shape feature.
BINS = (0.02, 0.1, 0.3, 0.6)


def shape(text: str, words: list[str]) -> list[float]:
    """Shares of words with odd marks, in capitals, that are marks alone, that repeat, and of repeated lines."""
    n = max(1, len(words))
    marks = len(_MARKS.findall(text))
    alone = words.count("|") + words.count("-") + words.count("*")
    lines = text.split("\n")
    return [
        min(1.0, marks / n),
        sum(map(str.isupper, words)) / n,
        min(1.0, alone / n),
        1 - len(set(words)) / n,
        1 - len(set(lines)) / len(lines),
    ]


def features(text: str | None) -> tuple[set[str], list[int]]:
    """The distinct lower-case words with their beginnings (marked ~), and the shape as bins."""
    text = text or ""
    words = text.split()
    bins = [i * (len(BINS) + 1) + sum(v >= b for b in BINS) for i, v in enumerate(shape(text, words))]
    seen = {w.strip(_ENDS) for w in text.lower().split()}
    starts = {f"{w[:k]}~" for w in seen for k in PREFIXES if len(w) > k}
    return seen | starts, bins


N_BINS = 5 * (len(BINS) + 1)


@dataclass(frozen=True)
class Model:
    """Weights by word, by bin, and the constant, of each head."""

    words: dict[str, tuple[float, ...]]
    bins: tuple[tuple[float, ...], ...]
    constant: tuple[float, ...]

    def text(self) -> str:
        """The model as JSON; ``parse`` reads it back exactly."""
        return json.dumps([self.words, self.bins, self.constant])

    @classmethod
    def parse(cls, text: str) -> Model:
        words, bins, constant = json.loads(text)
        return cls({k: tuple(v) for k, v in words.items()}, tuple(map(tuple, bins)), tuple(constant))

    def logits(self, text: str | None) -> list[float]:
        seen, bins = features(text)
        out = list(self.constant)
        for w in seen & self.words.keys():
            for h, x in enumerate(self.words[w]):
                out[h] += x
        for b in bins:
            for h, x in enumerate(self.bins[b]):
                out[h] += x
        return out


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float, rounds: int = 30) -> np.ndarray:
    """Ridge logistic regression by Newton steps; the last column is the constant and is not shrunk."""
    w = np.zeros(x.shape[1])
    penalty = np.full(x.shape[1], ridge)
    penalty[-1] = 1e-6
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + np.diag(penalty + 1e-9), x.T @ (p - y) + penalty * w)
        w -= step
        if np.abs(step).max() < 1e-6:
            break
    return w


def fit(rows: list[tuple[list[str], list[int], int, int]], *, least_docs: int = 6, chi: float = 25.0, most_words: int = 200, ridge: float = 0.3) -> Model:
    """Fit both heads on (words, bins, low, toxic); words are chosen by their chi-square with each label."""
    vocabulary: dict[str, int] = {}
    lists = [np.array([vocabulary.setdefault(w, len(vocabulary)) for w in words], dtype=np.int64) for words, *_ in rows]
    n, size = len(rows), len(vocabulary)
    names = list(vocabulary)
    labels = np.array([[low, toxic] for *_, low, toxic in rows], dtype=float).reshape(n, 2)
    df = np.bincount(np.concatenate([*lists, np.empty(0, dtype=np.int64)]), minlength=size).astype(float)
    word_weights: dict[str, list[float]] = {}
    bins = np.zeros((N_BINS, 2))
    constant = []
    for h in range(2):
        y = labels[:, h]
        pos = y.sum()
        if not 0 < pos < n:
            constant.append(-20.0 if pos == 0 else 20.0)
            continue
        hit = np.bincount(np.concatenate([*(v for v, l in zip(lists, y, strict=True) if l), np.empty(0, dtype=np.int64)]), minlength=size)
        expected = df * pos / n
        score = np.where(df >= least_docs, (hit - expected) ** 2 / np.maximum(1e-9, expected * (1 - pos / n) * np.maximum(1e-9, 1 - df / n)), 0.0)
        chosen = [int(i) for i in np.lexsort((names, -score))[:most_words] if score[i] > chi]
        place = {i: k for k, i in enumerate(chosen)}
        x = np.zeros((n, len(chosen) + N_BINS + 1))
        for r, (own, (_, b, *_)) in enumerate(zip(lists, rows, strict=True)):
            x[r, [place[i] for i in own.tolist() if i in place]] = 1
            x[r, [len(chosen) + k for k in b]] = 1
        x[:, -1] = 1
        w = _logistic(x, y, ridge)
        for i, k in place.items():
            word_weights.setdefault(names[i], [0.0, 0.0])[h] = float(w[k])
        bins[:, h] = w[len(chosen) : -1]
        constant.append(float(w[-1]))
    return Model({k: tuple(v) for k, v in word_weights.items()}, tuple(map(tuple, bins.tolist())), tuple(constant))


def _featurise(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("words", pa.list_(pa.string())), ("bins", pa.list_(pa.int64())), ("low", pa.int64()), ("toxic", pa.int64())])
    for batch in batches:
        both = [features(t.as_py()) for t in batch.column("text")]
        arrays = [pa.array([sorted(w) for w, _ in both], type=pa.list_(pa.string())), pa.array([b for _, b in both], type=pa.list_(pa.int64())), batch.column("low"), batch.column("toxic")]
        yield pa.RecordBatch.from_arrays(arrays, schema=schema)


def fit_on_labels(docs: DataFrame, labels: DataFrame, *, fit_rows: int = 4000, id_col: str = "doc_id", text_col: str = "text") -> Model:
    """Fit on at most ``fit_rows`` labelled documents, chosen by a hash of their ids.

    Rows with a null id or label take no part, nor do labels without a document;
    without any row both heads reject nothing.
    """
    bound_batches(docs.sparkSession)
    chosen = (
        labels.where(F.col(id_col).isNotNull() & F.col("quality").isNotNull() & F.col("toxic").isNotNull())
        .select(F.col(id_col).cast("long").alias("_id"), (F.lit(1) - F.col("quality")).cast("long").alias("low"), F.col("toxic").cast("long").alias("toxic"))
        .orderBy(F.xxhash64("_id"), "_id", "low", "toxic")
        .limit(fit_rows)
    )
    rows = docs.select(F.col(id_col).cast("long").alias("_id"), F.col(text_col).cast("string").alias("text")).join(F.broadcast(chosen), "_id")
    read = rows.select("text", "low", "toxic").mapInArrow(_featurise, "words array<string>, bins array<long>, low long, toxic long")
    # the sample is bounded, so one task fits the models, and the driver gets their weights alone
    made = read.repartition(1).mapInArrow(_fit_task(fit_rows), "model string").first()
    return Model.parse(made.model) if made else fit([])


def _fit_task(fit_rows: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = []
        for batch in batches:
            words, bins, low, toxic = (batch.column(c).to_pylist() for c in ("words", "bins", "low", "toxic"))
            got += [(w, b, min(1, max(0, x)), min(1, max(0, y))) for w, b, x, y in zip(words, bins, low, toxic, strict=True)]
        # in a fixed order, so that reruns fit the same model
        got.sort(key=lambda r: (r[2:], r[1], r[0]))
        yield pa.RecordBatch.from_arrays([pa.array([fit(got[:fit_rows]).text()])], names=["model"])

    return run


def _score(model: Model):
    schema = pa.schema([("doc_id", pa.int64()), ("tie", pa.int64()), ("host", pa.string()), ("path", pa.string()), ("low", pa.float64()), ("toxic", pa.float64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            logits = [model.logits(t.as_py()) for t in batch.column("text")]
            heads = [pa.array([row[h] for row in logits], type=pa.float64()) for h in range(2)]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("doc_id", "tie", "host", "path")), *heads], schema=schema)

    return run


def _sigmoid(x: Column) -> Column:
    return F.lit(1.0) / (F.lit(1.0) + F.exp(-x))


def _logit(p: Column) -> Column:
    return F.log(p / (F.lit(1.0) - p))


def _strength(groups: DataFrame, head: str, mean: float) -> float:
    """Pseudo-documents of the prior, by the method of moments over groups with at least two documents."""
    rate = F.col(f"{head}_sum") / F.col("n")
    row = groups.where("n > 1").agg(F.sum("n").alias("n"), F.sum(F.col("n") * (rate - F.lit(mean)) ** 2).alias("s"), F.count(F.lit(1)).alias("g")).first()
    if not row.g or row.g < 2:
        return 100.0
    between = row.s / row.n - mean * (1 - mean) * row.g / row.n
    return 10_000.0 if between <= 0 else min(10_000.0, max(10.0, mean * (1 - mean) / between - 1))


def judge(
    docs: DataFrame,
    labels: DataFrame,
    *,
    id_col: str = "doc_id",
    text_col: str = "text",
    host_col: str = "source",
    path_col: str = "lang",
    fit_rows: int = 4000,
    most_groups: int = 50_000,
    threshold: float = 0.3,
    model: Model | None = None,
) -> DataFrame:
    """doc_id, tie, source, lang, p_low, p_toxic, keep: one row per input row.

    ``keep`` is false where either probability reaches ``threshold``. Null and
    empty texts are scored by their shape alone; null hosts and paths are groups
    of their own; repeated rows get equal results. Without labels of both kinds
    a head rejects nothing. ``tie`` is the hash of the text. The table of groups
    is broadcast up to ``most_groups`` rows and joined by shuffle beyond. Other
    columns are not read; an empty table gives an empty result.
    """
    bound_batches(docs.sparkSession)
    model = model or fit_on_labels(docs, labels, fit_rows=fit_rows, id_col=id_col, text_col=text_col)
    rows = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        F.coalesce(F.xxhash64(F.col(text_col)), F.lit(0).cast("long")).alias("tie"),
        F.col(host_col).cast("string").alias("host"),
        F.col(path_col).cast("string").alias("path"),
        F.col(text_col).cast("string").alias("text"),
    )
    evidence = stored(rows.mapInArrow(_score(model), "doc_id long, tie long, host string, path string, low double, toxic double"), "evidence")
    sums = [F.sum(_sigmoid(F.col(h))).alias(f"{h}_sum") for h in HEADS]
    paths = stored(evidence.groupBy("host", "path").agg(F.count(F.lit(1)).alias("n"), *sums), "paths")
    hosts = paths.groupBy("host").agg(F.sum("n").alias("n"), *[F.sum(f"{h}_sum").alias(f"{h}_sum") for h in HEADS])
    hosts = stored(hosts, "hosts")
    total = hosts.agg(F.sum("n").alias("n"), *[F.sum(f"{h}_sum").alias(h) for h in HEADS]).first()
    mean = {h: min(1 - 1e-6, max(1e-6, (total[h] or 0.0) / max(1, total.n or 1))) for h in HEADS}
    m_host = {h: _strength(hosts, h, mean[h]) for h in HEADS}
    m_path = {h: _strength(paths, h, mean[h]) for h in HEADS}
    host_rate = [((F.col(f"{h}_sum") + F.lit(m_host[h] * mean[h])) / (F.col("n") + F.lit(m_host[h]))).alias(f"{h}_host") for h in HEADS]
    host_rates = hosts.select(F.col("host").alias("h"), *host_rate)
    path_rate = [((F.col(f"{h}_sum") + F.lit(m_path[h]) * F.col(f"{h}_host")) / (F.col("n") + F.lit(m_path[h]))).alias(f"{h}_path") for h in HEADS]
    rates = stored(paths.join(host_rates, paths["host"].eqNullSafe(host_rates["h"])).select(F.col("host").alias("h"), F.col("path").alias("p"), *path_rate), "rates")
    rates = small(rates, most_groups)
    joined = evidence.join(rates, evidence["host"].eqNullSafe(rates["h"]) & evidence["path"].eqNullSafe(rates["p"]))
    p = {h: _sigmoid(F.col(h) + _logit(F.col(f"{h}_path")) - F.lit(math.log(mean[h] / (1 - mean[h])))) for h in HEADS}
    keep = (p["low"] < F.lit(threshold)) & (p["toxic"] < F.lit(threshold))
    return joined.select(
        "doc_id", "tie", F.col("host").alias("source"), F.col("path").alias("lang"), F.round(p["low"], 6).alias("p_low"), F.round(p["toxic"], 6).alias("p_toxic"), keep.alias("keep")
    )


def keep_good(docs: DataFrame, labels: DataFrame, **options: object) -> DataFrame:
    """The documents that ``judge`` keeps, with all their columns."""
    id_col, text_col = str(options.get("id_col", "doc_id")), str(options.get("text_col", "text"))
    good = judge(docs, labels, **options).where("keep").select(F.col("doc_id").alias("_id"), F.col("tie").alias("_tie"))
    tie = F.coalesce(F.xxhash64(F.col(text_col)), F.lit(0).cast("long"))
    return docs.join(good.hint("shuffle_hash"), docs[id_col].cast("long").eqNullSafe(good["_id"]) & (tie == good["_tie"]), "left_semi")
