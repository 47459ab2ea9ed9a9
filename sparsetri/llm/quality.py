"""Quality classifier: naive Bayes features under a linear hinge-loss model.

Indicators of byte n-grams (raw text and its letter shapes) are hashed to 2^18 features.  Each is scaled by the log
ratio of its smoothed class shares, rows are brought to unit length, and a hinge-loss model is fitted by dual coordinate
descent; a logistic curve fitted on rows kept aside turns margins into probabilities.

The fit uses at most `max_fit_rows` labelled rows (lowest hashes of their ids, so it is the same sample everywhere), and of these, in the
same order, as many as have `max_fit_features` features together; these two bounds are what makes the broadcast of the sample's labels
bounded, and the task that fits (a feature is four bytes there).  Only the model, of a fixed size, comes to the driver.  Scoring covers every
whole text in one scan without a shuffle.

Defined results: a null text is an empty one; an empty text has no features and gets the curve's value at the bias.
Labels that are null or not 0/1 are ignored; several labels of one document count each.  Without labels of both classes all
documents get the smoothed share of label 1.  Repeated rows repeat their score, and equal texts have equal scores.  Only text decides a
score.  A row with a null doc_id is scored like any other, is not held out, and finds no label.  Columns of docs pass through, and one named
like the score is replaced.  An empty table gives an empty one.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import arrow_rows, claim_cache, stored

BITS = 18
SIZE = 1 << BITS


def _shape_table() -> bytes:
    """a for lower case and bytes of other alphabets, A for upper case, 9 for digits; the rest stands for itself."""
    kind = {**{c: "a" for c in range(97, 123)}, **{c: "a" for c in range(128, 256)}, **{c: "A" for c in range(65, 91)}, **{c: "9" for c in range(48, 58)}}
    return bytes(ord(kind[c]) if c in kind else c for c in range(256))


SHAPES = _shape_table()


class Indicators:
    """Sorted feature numbers of a text.  The marks are kept between calls, as clearing what was set is cheaper than a new array."""

    def __init__(self):
        self.seen = np.zeros(SIZE, bool)

    def of(self, text: str | None) -> np.ndarray:
        raw = (text or "").encode()
        for kind, data, n in ((1, raw, 3), (2, raw.translate(SHAPES), 5)):
            a = np.frombuffer(data, np.uint8).astype(np.uint64)
            if len(a) < n:
                continue
            code = np.full(len(a) - n + 1, kind, np.uint64)
            for k in range(n):
                code = code * np.uint64(257) + a[k : len(a) - n + 1 + k]
            self.seen[(code * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - BITS)] = True
        out = np.flatnonzero(self.seen).astype(np.int32)
        self.seen[out] = False
        return out


@dataclass(frozen=True)
class Model:
    weights: np.ndarray  # of a feature in a row of unit length: ratio times hinge weight
    ratios: np.ndarray
    bias: float
    slope: float
    offset: float

    def scores(self, rows: list[np.ndarray]) -> np.ndarray:
        margin = np.array([self.bias + (self.weights[x].sum() / np.sqrt((self.ratios[x] ** 2).sum() or 1.0) if len(x) else 0.0) for x in rows])
        return 1 / (1 + np.exp(-np.clip(self.slope * margin + self.offset, -500, 500)))


def log_count_ratios(rows: list[np.ndarray], y: np.ndarray, smooth: float = 1.0) -> np.ndarray:
    counts = np.full((2, SIZE), smooth)
    for x, label in zip(rows, y, strict=True):
        counts[label, x] += 1
    share = counts / np.array([[max((y == 0).sum(), 1) + 2 * smooth], [max((y == 1).sum(), 1) + 2 * smooth]])
    return np.log(share[1] / share[0])


class UnitRows(Sequence):
    """Ratios of each row's features, brought to unit length; made when asked for, as they take twice the memory of the features."""

    def __init__(self, rows: list[np.ndarray], ratios: np.ndarray):
        self.rows, self.ratios = rows, ratios
        self.lengths = [np.sqrt((v @ v) or 1.0) for v in (ratios[x] for x in rows)]

    def __len__(self) -> int:
        return len(self.rows)

    def __getitem__(self, i: int) -> np.ndarray:
        return self.ratios[self.rows[i]] / self.lengths[i]


def dual_coordinate_descent(rows: list[np.ndarray], values: Sequence[np.ndarray], y: np.ndarray, c: np.ndarray, epochs: int = 12, seed: int = 7) -> tuple[np.ndarray, float]:
    """min ||w||^2/2 + sum c_i max(0, 1 - y_i w.x_i), one dual variable at a time in shuffled order; rows have unit length,
    and the bias is the weight of a constant 1."""
    w, bias = np.zeros(SIZE), 0.0
    alpha, order = np.zeros(len(rows)), np.random.default_rng(seed)
    for _ in range(epochs):
        moved = 0.0
        for i in order.permutation(len(rows)):
            x, v = rows[i], values[i]
            slack = 1 - y[i] * (w[x] @ v + bias)
            new = min(max(alpha[i] + slack / (v @ v + 1), 0.0), c[i])
            if step := new - alpha[i]:
                alpha[i] = new
                w[x] += step * y[i] * v
                bias += step * y[i]
                moved = max(moved, abs(step))
        if moved < 1e-4:
            break
    return w, bias


def _logistic_curve(margin: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and offset by Newton steps on smoothed targets."""
    up, down = (y == 1).sum(), (y == 0).sum()
    goal = np.where(y == 1, (up + 1) / (up + 2), 1 / (down + 2))
    a, b = 1.0, 0.0
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a * margin + b, -30, 30)))
        g, h = p - goal, np.maximum(p * (1 - p), 1e-9)
        m = np.array([[(h * margin * margin).sum() + 1e-6, (h * margin).sum()], [(h * margin).sum(), h.sum() + 1e-6]])
        step = np.linalg.solve(m, np.array([(g * margin).sum(), g.sum()]))
        a, b = a - step[0], b - step[1]
        if np.abs(step).max() < 1e-8:
            break
    return float(a), float(b)


def fit_rows(rows: list[np.ndarray], y: np.ndarray, cost: float = 1.0) -> Model:
    """Every fifth row is kept aside for the curve."""
    none = np.zeros(SIZE)
    if len(rows) == 0 or len(set(y.tolist())) < 2:
        share = (y.sum() + 1) / (len(y) + 2)
        return Model(none, none, 0.0, 0.0, float(np.log(share / (1 - share))))
    aside = np.arange(len(rows)) % 5 == 4
    if len(rows) < 50 or len(set(y[~aside].tolist())) < 2 or len(set(y[aside].tolist())) < 2:
        aside[:] = False
    train = np.flatnonzero(~aside)
    trained = [rows[i] for i in train]
    ratios = log_count_ratios(trained, y[train])
    sign = np.where(y[train] == 1, 1.0, -1.0)
    share = np.array([(y[train] == 0).mean(), (y[train] == 1).mean()])
    w, bias = dual_coordinate_descent(trained, UnitRows(trained, ratios), sign, cost / (2 * share[y[train]]))
    model = Model(ratios * w, ratios, bias, 1.0, 0.0)
    curve = np.flatnonzero(aside) if aside.any() else train
    margin = np.array([model.bias + (model.weights[x].sum() / np.sqrt((ratios[x] ** 2).sum() or 1.0) if len(x) else 0.0) for x in (rows[i] for i in curve)])
    return Model(model.weights, ratios, bias, *_logistic_curve(margin, y[curve]))


def _featurize(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    add, rest = arrow_rows(pa.schema([("place", pa.int64()), ("label", pa.int64()), ("features", pa.list_(pa.int32()))]))
    make = Indicators()
    for batch in batches:
        for place, label, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
            x = make.of(text.as_py())
            if (full := add((place, label, x), 4 * len(x))) is not None:
                yield full
    yield from rest()


MODEL = pa.schema([("weights", pa.binary()), ("ratios", pa.binary()), ("bias", pa.float64()), ("slope", pa.float64()), ("offset", pa.float64())])
MODEL_DDL = "weights binary, ratios binary, bias double, slope double, offset double"


def _fit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row, the model of all rows (label, features) in their order."""
    claim_cache("quality", lambda: None)
    rows, y = [], []
    for batch in batches:
        y += batch.column(0).to_pylist()
        rows += [x.values.to_numpy(zero_copy_only=False) for x in batch.column(1)]
    m = fit_rows(rows, np.array(y, np.int64))
    made = (m.weights.tobytes(), m.ratios.tobytes(), m.bias, m.slope, m.offset)
    yield pa.RecordBatch.from_arrays([pa.array([v], t.type) for v, t in zip(made, MODEL, strict=True)], schema=MODEL)


def fit(docs: DataFrame, labels: DataFrame, max_fit_rows: int = 12000, max_fit_features: int = 48_000_000) -> Model:
    """labels: doc_id, quality.  One task fits on the bounded sample's features; the driver, which has the least memory, gets the model."""
    place = F.xxhash64(F.lit("fit"), "doc_id")
    sample = labels.where(F.col("doc_id").isNotNull() & F.col("quality").isin(0, 1)).select("doc_id", F.col("quality").cast("long").alias("label"), place.alias("place"))
    sample = sample.orderBy("place", "doc_id", "label").limit(max_fit_rows)
    found = docs.select("doc_id", "text").join(F.broadcast(sample), "doc_id").select("place", "label", "text").mapInArrow(_featurize, "place long, label long, features array<int>")
    found = stored(found, "fit-features")
    upto = F.sum(F.size("features")).over(Window.orderBy("place", "label").rowsBetween(Window.unboundedPreceding, 0))  # of max_fit_rows rows at most
    last = found.select("place", "label", upto.alias("upto")).where(F.col("upto") <= max_fit_features).agg(F.max(F.struct("place", "label")).alias("last")).first()["last"]
    found = found if last is None else found.where(F.struct("place", "label") <= F.struct(F.lit(last["place"]).cast("long"), F.lit(last["label"]).cast("long")))
    made = found.coalesce(1).sortWithinPartitions("place", "label").select("label", "features").mapInArrow(_fit, MODEL_DDL).first()
    return Model(np.frombuffer(made["weights"]), np.frombuffer(made["ratios"]), made["bias"], made["slope"], made["offset"])


def score(docs: DataFrame, model: Model, name: str = "score") -> DataFrame:
    """docs' columns and `name` (0 to 1, higher: label 1 likelier); a column of that name is replaced."""
    docs = docs.drop(name)
    place = docs.columns.index("text")
    shared = docs.sparkSession.sparkContext.broadcast(model)  # three arrays of fixed size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim_cache("quality", lambda: None)
        make = Indicators()
        for batch in batches:
            for start in range(0, batch.num_rows, 1024):
                part = batch.slice(start, 1024)
                got = shared.value.scores([make.of(x.as_py()) for x in part.column(place)])
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(got, pa.float64())], names=[*part.schema.names, name])

    from pyspark.sql.types import StructField, StructType

    fields = [StructField(f.name, f.dataType, True) for f in docs.schema.fields]
    from pyspark.sql.types import DoubleType

    return docs.mapInArrow(run, StructType([*fields, StructField(name, DoubleType(), True)]))


def held_out(doc_id="doc_id"):
    """Never null: a row without an id is not held out."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 4 == 2, F.lit(False))
