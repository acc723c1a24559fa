"""Quality classifier: Naive Bayes support vectors.

Indicators of word and word-shape n-grams are scaled by the logarithm of the ratio of their smoothed class
frequencies, counted over all labelled training rows; a linear hinge-loss model is fitted to the scaled, length-normed
indicators by dual coordinate descent, and its margins are mapped to probabilities on rows set aside.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from replica_sync.llm.common import Words, by_place, kept_as_table, mixed, pick, small_batches, texts_of, trim

#: Hashed features; bound of what is counted and sent.
BITS = 18
#: The model is fitted to at most so many labelled training rows, first in a seeded order (the counts cover all).
FITTED_ROWS = 6000


def features(texts: list[bytes], bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """(doc, feature), distinct and sorted: words, pairs of words, shapes, pairs of shapes, and words said on end."""
    words, shapes = Words(texts), Words(texts, shapes=True)

    def coded(salt: int, doc: np.ndarray, keys: np.ndarray) -> np.ndarray:
        return doc.astype(np.uint64) << np.uint64(bits) | mixed(keys + np.uint64(salt)) >> np.uint64(64 - bits)

    found = []
    for salt, w in ((11, words), (23, shapes)):
        same = w.doc[1:] == w.doc[:-1]
        pairs = (w.hash[:-1] * np.uint64(0x9FB21C651E98DF25) + w.hash[1:])[same]
        found += [coded(salt, w.doc, w.hash), coded(salt + 1, w.doc[1:][same], pairs)]
    same = np.concatenate([(words.hash[1:] == words.hash[:-1]) & (words.doc[1:] == words.doc[:-1]), [False]])
    run = np.concatenate([[0], np.cumsum(same)])
    for k, more in enumerate((2, 4, 8)):  # a word said 3, 5 or 9 times on end
        start = np.flatnonzero(run[more:] - run[:-more] == more)
        found.append(coded(31 + k, words.doc[start], np.zeros(len(start), dtype=np.uint64)))
    every = np.unique(np.concatenate(found))
    return (every >> np.uint64(bits)).astype(np.int64), (every & np.uint64((1 << bits) - 1)).astype(np.int64)


def log_count_ratio(good: np.ndarray, bad: np.ndarray, smoothing: float = 1.0) -> np.ndarray:
    p, q = good + smoothing, bad + smoothing
    return np.log(p / p.sum()) - np.log(q / q.sum())


def dual_coordinate_descent(rows: list[tuple[np.ndarray, np.ndarray]], sign: np.ndarray, cost: np.ndarray, size: int, rounds: int = 12, seed: int = 5) -> np.ndarray:
    """Weights of the squared-hinge model: each step solves one row's dual variable exactly."""
    weight, dual = np.zeros(size), np.zeros(len(rows))
    square = np.array([x @ x for _, x in rows])
    random = np.random.default_rng(seed)
    for _ in range(rounds):
        largest = 0.0
        for i in random.permutation(len(rows)):
            at, x = rows[i]
            slope = sign[i] * (weight[at] @ x) - 1 + dual[i] / (2 * cost[i])
            new = max(dual[i] - slope / (square[i] + 1 / (2 * cost[i])), 0.0)
            if new != dual[i]:
                weight[at] += (new - dual[i]) * sign[i] * x
                largest = max(largest, abs(new - dual[i]))
                dual[i] = new
        if largest < 1e-4:
            break
    return weight


def calibrated(margin: np.ndarray, good: np.ndarray, rounds: int = 50) -> tuple[float, float]:
    """Slope and offset of the logistic curve through margins, by damped Newton steps with smoothed targets."""
    n1, n0 = good.sum(), (~good).sum()
    target = np.where(good, (n1 + 1) / (n1 + 2), 1 / (n0 + 2))
    a, b = 1.0, 0.0
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(a * margin + b, -50, 50)))
        w, g = p * (1 - p) + 1e-9, p - target
        hessian = np.array([[(w * margin**2).sum() + 1e-6, (w * margin).sum()], [(w * margin).sum(), w.sum() + 1e-6]])
        step = np.linalg.solve(hessian, np.array([(g * margin).sum() + 1e-6 * a, g.sum()]))
        a, b = a - step[0], b - step[1]
        if np.abs(step).max() < 1e-6:
            break
    return float(a), float(b)


def _designs(texts: list[bytes], ratio: np.ndarray, bits: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """Per text: places of its features and of the constant, their scaled values in unit length."""
    doc, feature = features(texts, bits)
    cut = np.searchsorted(doc, np.arange(len(texts) + 1))
    out = []
    for a, b in zip(cut, cut[1:]):
        at = feature[a:b]
        x = ratio[at]
        norm = np.sqrt(x @ x) or 1.0
        out.append((np.append(at, 1 << bits), np.append(x / norm, 1.0)))
    return out


class QualityModel:
    """Weights of features (already times their ratios), offset and logistic curve."""

    def __init__(self, ratio: np.ndarray, weight: np.ndarray, curve: tuple[float, float], bits: int):
        self.ratio, self.weight, self.curve, self.bits = ratio.astype(np.float32), (weight[:-1] * ratio).astype(np.float32), curve, bits
        self.offset = float(weight[-1])

    def score(self, texts: list[bytes]) -> np.ndarray:
        doc, feature = features(texts, self.bits)
        n = len(texts)
        length = np.sqrt(np.bincount(doc, self.ratio[feature].astype(float) ** 2, minlength=n))
        margin = np.bincount(doc, self.weight[feature].astype(float), minlength=n) / np.where(length > 0, length, 1.0) + self.offset
        a, b = self.curve
        return 1 / (1 + np.exp(-np.clip(a * margin + b, -50, 50)))


def fitted_model(labelled: DataFrame, bits: int = BITS, rows: int = FITTED_ROWS, cost: float = 1.0, seed: int = 5) -> QualityModel:
    """labelled: doc_id, text, label (1 good, 0 bad). Counts over all rows, fit over a bounded sample.

    One class alone, or no labelled rows, gives a model that scores every text alike by the smoothed share.
    """
    size = 1 << bits

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals = np.zeros((2, size + 1))
        for batch in small_batches(batches, "text"):
            good = np.array(batch.column(2).to_pylist(), dtype=np.int64)
            doc, feature = features(texts_of(batch), bits)
            for c in (0, 1):
                totals[c, :size] += np.bincount(feature[good[doc] == c], minlength=size)
                totals[c, size] += (good == c).sum()
        some = np.flatnonzero(totals.any(axis=0))
        yield pa.record_batch([pa.array(some), pa.array(totals[0, some]), pa.array(totals[1, some])], names=["feature", "bad", "good"])

    counted = labelled.select("doc_id", "text", "label").mapInArrow(count, "feature bigint, bad double, good double")
    table = counted.groupBy("feature").agg(F.sum("bad").alias("bad"), F.sum("good").alias("good")).toArrow()  # at most 2**bits + 1 rows
    sums = np.zeros((2, size + 1))
    place = table.column("feature").to_numpy()
    sums[0, place], sums[1, place] = table.column("bad").to_numpy(), table.column("good").to_numpy()
    bad, good = sums[0, size], sums[1, size]
    if not bad or not good:
        share = (good + 1) / (good + bad + 2)
        return QualityModel(np.zeros(size), np.zeros(size + 1), (0.0, float(np.log(share / (1 - share)))), bits)
    ratio = log_count_ratio(sums[1, :size], sums[0, :size])

    def fit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        designs, labels = [], []
        for batch in small_batches(batches, "text"):
            designs += _designs(texts_of(batch), ratio, bits)
            labels += batch.column(2).to_pylist()
        if not labels:
            return
        is_good = np.array(labels, dtype=bool)
        n = len(labels)
        aside = np.arange(n) % 4 == 3 if n >= 40 else np.ones(n, dtype=bool)
        used = ~aside if n >= 40 else aside
        share = [max((is_good[used] == c).sum(), 1) for c in (False, True)]
        rows_used = [d for d, u in zip(designs, used) if u]
        costs = np.array([cost * used.sum() / (2 * share[int(g)]) for g in is_good[used]])
        weight = dual_coordinate_descent(rows_used, np.where(is_good[used], 1.0, -1.0), costs, size + 1, seed=seed)
        margin = np.array([weight[at] @ x for (at, x), s in zip(designs, aside) if s])
        curve = calibrated(margin, is_good[aside])
        yield pa.record_batch([pa.array([weight.tobytes()]), pa.array([curve[0]]), pa.array([curve[1]])], names=["weight", "a", "b"])

    order = F.md5(F.concat_ws("#", F.lit(str(seed)), F.col("doc_id").cast("string")))
    share = min(1.0, 1.5 * rows / (good + bad) + 64 / (good + bad))  # more than rows of them, so that little is sorted
    first = F.conv(F.substring(order, 1, 8), 16, 10).cast("bigint") <= int(share * 2**32)
    sample = labelled.select("doc_id", "text", "label").where(first).orderBy(order, "text").limit(rows)
    found = sample.mapInArrow(fit, "weight binary, a double, b double").first()
    return QualityModel(ratio, np.frombuffer(found["weight"]), (found["a"], found["b"]), bits)


def with_labels(rows: DataFrame, known: DataFrame) -> DataFrame:
    """Rows with their labels, kept as a table. Always by a merge join: labels grow with the documents."""
    return kept_as_table(rows.join(known.hint("merge"), "doc_id"), "labelled-rows")


def score_quality(docs: DataFrame, labels: DataFrame, doc_id: str = "doc_id", text: str = "text", label: str = "quality", held_out=None, **options) -> DataFrame:
    """doc_id, held_out, score, predicted of every row.

    held_out: a boolean Column over doc_id, by default crc32(doc_id) mod 3 is 1; only the other rows' labels
    are learnt from, each with the text of its row (rows with equal ids all count). A null or empty text has
    no features and gets the model's score of nothing; null labels are left out; an empty table gives
    an empty result; other columns are not read.
    """
    rows = pick(docs, doc_id=doc_id, text=text)
    if held_out is None:
        held_out = F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")) % 3 == 1
    marked = rows.withColumn("held_out", held_out)
    known = pick(labels, doc_id=doc_id, label=label).where(F.col("label").isin(0, 1)).dropDuplicates(["doc_id", "label"]).where(~held_out)
    model = fitted_model(with_labels(marked.where(~F.col("held_out")).drop("held_out"), known), **options)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text"):
            score = model.score(texts_of(batch))
            yield pa.record_batch([batch.column(0), batch.column(2), pa.array(score), pa.array((score >= 0.5).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])
        trim()

    return marked.mapInArrow(run, f"doc_id {dict(rows.dtypes)['doc_id']}, held_out boolean, score double, predicted int")


def keep_good(docs: DataFrame, labels: DataFrame, least: float = 0.5, **options) -> DataFrame:
    """The rows of docs, all columns of whatever names, whose score is at least least; learnt from the labels by score_quality's rules.

    A null or empty text has the score of nothing; repeated rows stay or go together; an empty table gives an empty result.
    """
    rows = pick(docs, doc_id="doc_id", text="text")
    held_out = F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")) % 3 == 1
    known = pick(labels, doc_id="doc_id", label="quality").where(F.col("label").isin(0, 1)).dropDuplicates(["doc_id", "label"]).where(~held_out)
    model = fitted_model(with_labels(rows.where(~held_out), known), **options)
    schema, text = docs.schema, f"c{docs.columns.index('text')}"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, text):
            kept = batch.filter(pa.array(model.score(texts_of(batch, text)) >= least))
            yield pa.record_batch(kept.columns, names=schema.names)
        trim()

    return by_place(docs).mapInArrow(run, schema)
