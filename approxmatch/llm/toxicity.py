"""Toxicity by a classifier chain.

Categories form a chain: "low_quality" (label quality = 0) first, then "toxic" (label toxic = 1). Each has a logistic
model over the presence of hashed words and word beginnings (six bytes); the models after the first also see the log
odds of the categories before them. In training those come out of fold: the sample is dealt into FOLDS parts by a
hash of doc_id, and a part's odds come from models that haven't seen it. In scoring they come from the models
trained on the whole sample.

The classifier is trained on a bounded sample: of each value of the last category at most SAMPLE labelled documents,
the first by a hash of doc_id. Its features are chosen by their G statistic, at most FEATURES of those that occur in
MIN_DOCS sampled documents; they are counted as a table, and only the sample's chosen features reach the driver: at
most 2 * SAMPLE lists of FEATURES numbers. The models of a category (one a fold, and one of all) are fitted as tasks.
Classes weigh as among all labels. A document is toxic if the last probability is at least the threshold: the least one
from 0.5 on whose out-of-fold precision reaches PRECISION, or, if none does, the least of those of the highest precision.

Defined cases: a null text has no features; words are runs of ASCII letters and digits and of bytes from 0x80, A-Z
lower-cased, and a long text's features are all different ones of it; labels that are null or whose document is missing
don't count; with no label of a value (or none at all) a category's probability is the share of its labels (0 without
labels), and nothing is rejected; repeated labels and repeated rows count once each, and equal texts get equal results;
of labels with one hash the smaller doc_id comes first into the sample, of features with one statistic the smaller
hash; an empty table gives an empty result; other columns aren't read, and `filtered` passes them on.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import U, chunks, keep, lowered, mix, scratch, seeds, span_hashes

SAMPLE = 4000
FOLDS = 4
BITS = 20
BEGINNING = 6
MIN_DOCS = 4
FEATURES = 4000
PRECISION = 0.98
RIDGE = 1e-3
STEPS = 400
CATEGORIES = (("low_quality", "quality", 0), ("toxic", "toxic", 1))

_LETTER = np.zeros(256, bool)
_LETTER[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True
_SEED = seeds(1, 8888)[0]


def letter_spans(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and row of each run of letters and digits."""
    if not len(data):
        none = np.zeros(0, np.int64)
        return none, none, none
    inside = _LETTER[data]
    edge = np.zeros(len(data) + 1, bool)
    edge[at] = True
    starts = np.flatnonzero(inside & (~np.concatenate([[False], inside[:-1]]) | edge[:-1]))
    ends = np.flatnonzero(inside & (~np.concatenate([inside[1:], [False]]) | edge[1:])) + 1
    return starts, ends, np.searchsorted(at, starts, "right") - 1


def hashed_features(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(features, rows), with repeats."""
    data = lowered(data)
    starts, ends, row = letter_spans(data, at)
    with np.errstate(over="ignore"):
        whole = span_hashes(data, starts, ends)
        begin = mix(span_hashes(data, starts, np.minimum(ends, starts + BEGINNING)) ^ _SEED)
    shift = U(64 - BITS)
    return np.concatenate([whole >> shift, begin >> shift]).astype(np.int64), np.concatenate([row, row])


def feature_lists(docs: DataFrame, *carried: str) -> DataFrame:
    """doc_id, the carried columns, features (different ones, sorted)."""
    kinds = dict(docs.dtypes)
    schema = ", ".join(["doc_id long", *(f"{c} {kinds[c]}" for c in carried), "features array<int>"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for start, end, data, at in chunks(b[b.num_columns - 1]):
                f, r = hashed_features(data, at)
                key = np.unique(r << BITS | f)
                edges = np.searchsorted(key, np.arange(end - start + 1) << BITS).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(edges), pa.array((key & ((1 << BITS) - 1)).astype(np.int32)))
                yield pa.RecordBatch.from_arrays([*(b[i].slice(start, end - start) for i in range(b.num_columns - 1)), lists], ["doc_id", *carried, "features"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), *carried, "text").mapInArrow(run, schema)


@dataclass
class Linear:
    bias: float
    weights: np.ndarray
    before: np.ndarray  # weights of the earlier categories' log odds

    def odds(self, cols: np.ndarray, rows: np.ndarray, n: int, earlier: np.ndarray) -> np.ndarray:
        return self.bias + np.bincount(rows, weights=self.weights[cols], minlength=n) + earlier @ self.before


@dataclass
class Chain:
    names: tuple[str, ...]
    places: np.ndarray  # of each hashed feature among the chosen ones, or -1
    models: list[Linear]
    threshold: float

    def probabilities(self, f: np.ndarray, r: np.ndarray, n: int) -> np.ndarray:
        """(n, categories) from hashed features with rows."""
        c = self.places[f]
        there = c >= 0
        size = max(len(self.models[0].weights), 1) if self.models else 1
        key = np.unique(r[there] * size + c[there])
        cols, rows = key % size, key // size
        odds = np.zeros((n, 0))
        for m in self.models:
            odds = np.hstack([odds, m.odds(cols, rows, n, odds)[:, None]])
        return sigmoid(odds)


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


def fit(cols: np.ndarray, rows: np.ndarray, size: int, earlier: np.ndarray, y: np.ndarray, weight: np.ndarray) -> Linear:
    """Weighted logistic regression with a ridge, by accelerated gradient steps."""
    n, k = len(y), earlier.shape[1]
    share = float(np.clip((weight * y).sum() / max(weight.sum(), 1e-9), 1e-6, 1 - 1e-6)) if n else 1e-6
    model = Linear(float(np.log(share / (1 - share))), np.zeros(size), np.zeros(k))
    if n == 0 or y.min() == y.max():
        return model
    weight = weight / weight.sum()
    # Per-coordinate steps from the diagonal of the bound on the curvature, with Adam's moments.
    m, v = [np.zeros(size), np.zeros(k), 0.0], [np.zeros(size), np.zeros(k), 0.0]
    rate = 0.1
    for t in range(1, STEPS + 1):
        error = weight * (sigmoid(model.odds(cols, rows, n, earlier)) - y)
        g = [np.bincount(cols, weights=error[rows], minlength=size) + RIDGE * model.weights / max(n, 1) * 10, earlier.T @ error, error.sum()]
        values = [model.weights, model.before, model.bias]
        for i in range(3):
            m[i] = 0.9 * m[i] + 0.1 * g[i]
            v[i] = 0.999 * v[i] + 0.001 * g[i] ** 2
            values[i] = values[i] - rate * (m[i] / (1 - 0.9**t)) / (np.sqrt(v[i] / (1 - 0.999**t)) + 1e-8)
        model = Linear(float(values[2]), values[0], values[1])
        rate *= 0.995
    return model


def sampled(labels: DataFrame, columns: list[str], last: str, value: int, most: int = SAMPLE) -> DataFrame:
    """doc_id and label columns of at most `most` labelled documents of each value of the last category."""
    marked = labels.select(F.col("doc_id").cast("long").alias("doc_id"), *columns).where("doc_id is not null").dropna(subset=columns)
    order = [F.xxhash64(F.col("doc_id")), F.col("doc_id")]
    is_last = F.col(last) == value
    return marked.where(is_last).orderBy(*order).limit(most).unionByName(marked.where(~is_last).orderBy(*order).limit(most))


def chosen_features(rows: DataFrame, categories, shares: dict[str, float], n: int) -> np.ndarray:
    """The hashed features with the largest G statistic over any category."""
    on = [F.sum((F.col(c) == v).cast("long")).alias(f"on_{name}") for name, c, v in categories]
    counts = rows.select(*{c for _, c, _ in categories}, F.explode("features").alias("f")).groupBy("f").agg(F.count(F.lit(1)).alias("present"), *on).where(F.col("present") >= MIN_DOCS)

    def g(name: str) -> Column:
        hit, p = F.col(f"on_{name}").cast("double"), shares[name]
        part = lambda x, q: F.when((x > 0) & F.lit(q > 0), x * F.log(x / (F.col("present") * max(q, 1e-300)))).otherwise(F.lit(0.0))
        return part(hit, p) + part(F.col("present") - hit, 1 - p)

    best = F.round(F.greatest(F.lit(0.0), *(g(name) for name, _, _ in categories)), 9)
    return counts.select("f", best.alias("g")).where("g > 3").orderBy(F.desc("g"), "f").limit(FEATURES).toArrow()["f"].to_numpy().astype(np.int64)


def fitted(docs: DataFrame, cols: np.ndarray, rows: np.ndarray, size: int, earlier: np.ndarray, y: np.ndarray, weight: np.ndarray, fold: np.ndarray) -> list[Linear]:
    """The model without each fold, and the model of all, one task each."""
    shared = docs.sparkSession.sparkContext.broadcast((cols, rows, size, earlier, y, weight, fold))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cols, rows, size, earlier, y, weight, fold = shared.value
        for b in batches:
            for k in b[0].to_pylist():
                inside = fold != k  # the last number is no fold's
                renamed, use = np.cumsum(inside) - 1, inside[rows]
                m = fit(cols[use], renamed[rows[use]], size, earlier[inside], y[inside], weight[inside])
                yield pa.RecordBatch.from_arrays([pa.array([k], pa.int64()), pa.array([m.bias]), pa.array([m.weights.tobytes()], pa.binary()), pa.array([m.before.tobytes()], pa.binary())], ["k", "bias", "weights", "before"])

    out = docs.sparkSession.range(0, FOLDS + 1, 1, FOLDS + 1).mapInArrow(run, "k long, bias double, weights binary, before binary").collect()
    shared.unpersist()
    return [Linear(r["bias"], np.frombuffer(bytes(r["weights"])), np.frombuffer(bytes(r["before"]))) for r in sorted(out, key=lambda r: r["k"])]


def best_threshold(p: np.ndarray, y: np.ndarray, weight: np.ndarray) -> float:
    """The least of the thresholds that reach PRECISION, else the least of the highest precision; 2 without any."""
    best, found = -1.0, 2.0
    for c in np.arange(0.5, 0.99, 0.02):
        over = p >= c
        if over.any():
            precision = float((weight * y)[over].sum() / weight[over].sum())
            if precision >= PRECISION:
                return float(c)
            if precision > best:
                best, found = precision, float(c)
    return found


def train(docs: DataFrame, labels: DataFrame, categories=CATEGORIES, most: int = SAMPLE) -> Chain:
    with scratch():
        return _train(docs, labels, categories, most)


def _train(docs: DataFrame, labels: DataFrame, categories, most: int) -> Chain:
    columns = sorted({c for _, c, _ in categories})
    _, last, value = categories[-1]
    names = tuple(name for name, _, _ in categories)
    sample = sampled(labels, columns, last, value, most)
    # The sample has at most 2 * SAMPLE rows of three numbers: its size is a parameter, not the data's.
    rows = keep(feature_lists(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(sample), "doc_id"), *columns))
    marked = labels.where("doc_id is not null").dropna(subset=columns)
    of = rows.agg(F.count(F.lit(1)).alias("n"), *(F.avg((F.col(c) == v).cast("double")).alias(f"p_{name}") for name, c, v in categories)).first()
    places = np.full(1 << BITS, -1, np.int32)
    if not of["n"]:
        return Chain(names, places, [Linear(-40.0, np.zeros(0), np.zeros(k)) for k in range(len(categories))], 2.0)
    chosen = chosen_features(rows, categories, {name: of[f"p_{name}"] for name in names}, of["n"])
    places[chosen] = np.arange(len(chosen))
    one = docs.sparkSession.createDataFrame([(chosen.tolist(),)], "chosen array<int>")
    table = rows.crossJoin(F.broadcast(one)).select("doc_id", *columns, F.array_intersect("features", "chosen").alias("features"), F.size("features").alias("all")).toArrow()
    table = table.take(pa.array(np.lexsort((table["all"].to_numpy(), table["doc_id"].to_numpy()))))  # tasks end in any order
    n, ids, lists = table.num_rows, table["doc_id"].to_numpy(), table["features"].combine_chunks()
    f = lists.values.to_numpy()[lists.offsets[0].as_py() : lists.offsets[-1].as_py()].astype(np.int64)
    cols, rws = places[f].astype(np.int64), np.repeat(np.arange(n), np.diff(lists.offsets.to_numpy()))
    targets = {name: (table[c].to_numpy() == v).astype(float) for name, c, v in categories}
    y = targets[names[-1]]
    all_last = marked.agg(F.avg((F.col(last) == value).cast("double"))).first()[0] or 0.0
    weight = np.where(y > 0, all_last / max(y.mean(), 1e-9), (1 - all_last) / max(1 - y.mean(), 1e-9))
    with np.errstate(over="ignore"):
        fold = (mix(ids.view(U)) % U(FOLDS)).astype(np.int64)
    earlier, models, held = np.zeros((n, 0)), [], np.zeros(n)
    for name in names:
        parts = fitted(docs, cols, rws, len(chosen), earlier, targets[name], weight, fold)
        held = np.zeros(n)
        for k, part in enumerate(parts[:FOLDS]):
            held[fold == k] = part.odds(cols, rws, n, earlier)[fold == k]
        models.append(parts[FOLDS])
        earlier = np.hstack([earlier, held[:, None]])
    threshold = best_threshold(sigmoid(held), y, weight) if 0 < y.sum() < n else 2.0
    return Chain(names, places, models, threshold)


def scored(docs: DataFrame, chain: Chain) -> DataFrame:
    """doc_id, p_<category> of the chain, rejected."""
    shared = docs.sparkSession.sparkContext.broadcast(chain)
    names = [f"p_{c}" for c in chain.names]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for b in batches:
            for start, end, data, at in chunks(b[1]):
                p = model.probabilities(*hashed_features(data, at), end - start)
                yield pa.RecordBatch.from_arrays([b[0].slice(start, end - start), *(pa.array(x) for x in p.T), pa.array(p[:, -1] >= model.threshold)], ["doc_id", *names, "rejected"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, " + "".join(f"{c} double, " for c in names) + "rejected boolean")


def filtered(docs: DataFrame, chain: Chain) -> DataFrame:
    """The documents that aren't rejected, with all their columns. The verdict is a function of the text, so that
    rows need no join and repeated doc_ids no rule."""
    shared = docs.sparkSession.sparkContext.broadcast(chain)

    @F.pandas_udf("boolean")
    def toxic(texts):
        import pandas as pd

        column, out = pa.Array.from_pandas(texts, type=pa.string()), []
        for start, end, data, at in chunks(column):
            out.append(shared.value.probabilities(*hashed_features(data, at), end - start)[:, -1] >= shared.value.threshold)
        return pd.Series(np.concatenate(out) if out else np.zeros(0, bool))

    return docs.where(~toxic(F.col("text")))


__all__ = ["CATEGORIES", "Chain", "Column", "filtered", "letter_spans", "scored", "train"]
