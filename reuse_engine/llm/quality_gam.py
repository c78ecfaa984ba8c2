"""Quality classifier: a generalised additive model with pairwise interactions.

Text features are cut into at most ``BINS`` quantile bins.  Rounds of cyclic
boosting add a shallow tree to one feature's look-up table after another, on the
logistic gradient; then the pairs of features with the strongest interaction are
boosted the same way on two-dimensional tables.  A score is the sigmoid of the
sum of table entries: one vectorised addition for each feature and pair.

The model is fitted on at most about ``FIT_ROWS`` labelled rows, chosen by a hash
of the id among the allowed ones; features are taken from whole texts.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reuse_engine.llm.language_id import held_out
from reuse_engine.llm.worker_cache import limit_batches, released
from reuse_engine.storage import spread

FIT_ROWS = 20_000
BINS = 32
ROUNDS, PAIR_ROUNDS, RATE = 150, 60, 0.1
PAIRS = 6
LEAVES = 4
#: Least sum of weights in a leaf, and the ridge on its value.
MIN_WEIGHT, RIDGE = 1.0, 1.0

FEATURES = (
    "log_bytes", "log_words", "word_bytes", "symbols", "capitals", "digits", "stops", "shouts", "bars", "non_ascii",
    "variety", "top_word", "same_lines", "line_words", "packed", "word_spread",
)
_DELETE = {
    "symbols": b"#*$%&|<>", "capitals": bytes(range(65, 91)), "digits": b"0123456789", "stops": b".,;:", "shouts": b"!?",
    "bars": b"|", "non_ascii": bytes(range(128, 256)),
}


def features(body: bytes | None) -> tuple[float, ...]:
    """Measures of a whole text; null counts as empty."""
    body = body or b""
    n = len(body)
    words = body.split()
    k = len(words)
    shares = {name: (n - len(body.translate(None, chars))) / max(n, 1) for name, chars in _DELETE.items()}
    distinct = set(words)
    top = 0
    if k:
        lengths = np.fromiter(map(len, words), np.int64, k)
        mean, sd = float(lengths.mean()), float(lengths.std())
        _, times = np.unique(np.fromiter(map(hash, words), np.int64, k), return_counts=True)
        top = int(times.max())
    lines = [x for x in body.split(b"\n") if x.strip()]
    return (
        float(np.log2(n + 1)), float(np.log2(k + 1)), mean if k else 0.0,
        shares["symbols"], shares["capitals"], shares["digits"], shares["stops"], shares["shouts"], shares["bars"], shares["non_ascii"],
        len(distinct) / max(k, 1) ** 0.8, top / max(k, 1), 1 - len(set(lines)) / max(len(lines), 1), k / max(len(lines), 1),
        len(zlib.compress(body, 1)) / max(n, 1), sd if k else 0.0,
    )


def _tree(g: np.ndarray, h: np.ndarray) -> np.ndarray:
    """Leaf values per bin of a tree with up to LEAVES leaves over ordered bins."""
    cg, ch = np.concatenate([[0], np.cumsum(g)]), np.concatenate([[0], np.cumsum(h)])
    worth = lambda a, b: (cg[b] - cg[a]) ** 2 / (ch[b] - ch[a] + RIDGE)
    leaves = [(0, len(g))]
    while len(leaves) < LEAVES:
        best = (1e-9, None, None)
        for a, b in leaves:
            cut = np.arange(a + 1, b)
            if len(cut):
                ok = (ch[cut] - ch[a] >= MIN_WEIGHT) & (ch[b] - ch[cut] >= MIN_WEIGHT)
                gain = np.where(ok, worth(a, cut) + worth(cut, b) - worth(a, b), -1)
                i = int(gain.argmax())
                if gain[i] > best[0]:
                    best = (float(gain[i]), (a, b), int(cut[i]))
        if best[1] is None:
            break
        leaves.remove(best[1])
        leaves += [(best[1][0], best[2]), (best[2], best[1][1])]
    out = np.zeros(len(g))
    for a, b in leaves:
        out[a:b] = (cg[b] - cg[a]) / (ch[b] - ch[a] + RIDGE)
    return out


def _pair_tree(g: np.ndarray, h: np.ndarray) -> tuple[float, np.ndarray]:
    """Best cut on both axes: (gain, value per cell) of the four quadrants."""
    cg, ch = np.zeros((g.shape[0] + 1, g.shape[1] + 1)), np.zeros((h.shape[0] + 1, h.shape[1] + 1))
    cg[1:, 1:], ch[1:, 1:] = g.cumsum(0).cumsum(1), h.cumsum(0).cumsum(1)
    i, j = np.meshgrid(np.arange(1, g.shape[0]), np.arange(1, g.shape[1]), indexing="ij")
    if not i.size:
        return 0.0, np.zeros(g.shape)

    def quads(c: np.ndarray) -> list[np.ndarray]:
        a = c[i, j]
        return [a, c[i, -1] - a, c[-1, j] - a, c[-1, -1] - c[i, -1] - c[-1, j] + a]

    gs, hs = quads(cg), quads(ch)
    gain = sum(x * x / (y + RIDGE) for x, y in zip(gs, hs, strict=True)) - cg[-1, -1] ** 2 / (ch[-1, -1] + RIDGE)
    at = np.unravel_index(int(gain.argmax()), gain.shape)
    r, c = int(i[at]), int(j[at])
    v = [float(x[at] / (y[at] + RIDGE)) for x, y in zip(gs, hs, strict=True)]
    out = np.empty(g.shape)
    out[:r, :c], out[:r, c:], out[r:, :c], out[r:, c:] = v[0], v[1], v[2], v[3]
    return float(gain[at]), out


class AdditiveModel:
    """Cut points and tables; fitted by :meth:`fit`, scored by :meth:`score`."""

    def __init__(self) -> None:
        self.start = 0.0
        self.cuts: list[np.ndarray] = []
        self.tables: list[np.ndarray] = []
        self.pairs: list[tuple[int, int]] = []
        self.pair_tables: list[np.ndarray] = []

    def bins(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(c, x[:, f], side="right") for f, c in enumerate(self.cuts)], axis=1)

    def fit(self, x: np.ndarray, y: np.ndarray) -> AdditiveModel:
        """No row gives score 0.5, one class only its smoothed share."""
        share = (y.sum() + 0.5) / (len(y) + 1)
        self.start = float(np.log(share / (1 - share)))
        if not len(y) or y.min() == y.max():
            return self
        inner = np.linspace(0, 1, BINS + 1)[1:-1]
        self.cuts = [np.unique(np.quantile(x[:, f], inner)) for f in range(x.shape[1])]
        b = self.bins(x)
        sizes = [len(c) + 1 for c in self.cuts]
        self.tables = [np.zeros(n) for n in sizes]
        z = np.full(len(y), self.start)
        for _ in range(ROUNDS):
            for f, n in enumerate(sizes):
                g, h = self._gradient(z, y)
                step = RATE * _tree(np.bincount(b[:, f], g, n), np.bincount(b[:, f], h, n))
                self.tables[f] += step
                z += step[b[:, f]]
        g, h = self._gradient(z, y)
        gains = []
        for a in range(len(sizes)):
            for c in range(a + 1, len(sizes)):
                cell, shape = b[:, a] * sizes[c] + b[:, c], (sizes[a], sizes[c])
                flat = sizes[a] * sizes[c]
                gain, _ = _pair_tree(np.bincount(cell, g, flat).reshape(shape), np.bincount(cell, h, flat).reshape(shape))
                gains.append((-gain, a, c))
        self.pairs = [(a, c) for _, a, c in sorted(gains)[:PAIRS]]
        self.pair_tables = [np.zeros((sizes[a], sizes[c])) for a, c in self.pairs]
        for _ in range(PAIR_ROUNDS):
            for k, (a, c) in enumerate(self.pairs):
                g, h = self._gradient(z, y)
                cell, shape = b[:, a] * sizes[c] + b[:, c], self.pair_tables[k].shape
                flat = shape[0] * shape[1]
                _, step = _pair_tree(np.bincount(cell, g, flat).reshape(shape), np.bincount(cell, h, flat).reshape(shape))
                self.pair_tables[k] += RATE * step
                z += RATE * step[b[:, a], b[:, c]]
        return self

    @staticmethod
    def _gradient(z: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        p = 1 / (1 + np.exp(-z))
        return y - p, p * (1 - p)

    def score(self, x: np.ndarray) -> np.ndarray:
        z = np.full(len(x), self.start)
        if self.cuts:
            b = self.bins(x)
            for f, table in enumerate(self.tables):
                z += table[b[:, f]]
            for (a, c), table in zip(self.pairs, self.pair_tables, strict=True):
                z += table[b[:, a], b[:, c]]
        return 1 / (1 + np.exp(-z))


@released
def _measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = [list(features(t)) for t in batch.column(1).to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, pa.list_(pa.float64()))], names=["y", "x"])


def fit_quality(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", fit_rows: int = FIT_ROWS) -> AdditiveModel:
    """Fit on labelled rows that are not held out; of repeated labels of an id the largest counts."""
    allowed = labels.where(F.col(id_col).isNotNull() & F.col(label_col).isNotNull() & ~held_out(id_col))
    every = max(1, -(-allowed.count() // fit_rows))
    chosen = allowed.where(F.pmod(F.xxhash64(id_col), F.lit(every)) == 0).groupBy(id_col).agg(F.max(label_col).cast("int").alias("y"))
    rows = docs.select(id_col, F.col(text_col).cast("binary").alias("body")).join(F.broadcast(chosen), id_col)
    got = rows.select("y", "body").mapInArrow(_measure, "y int, x array<double>").toPandas()
    if not len(got):
        return AdditiveModel().fit(np.zeros((0, len(FEATURES))), np.zeros(0))
    x, y = np.array(got["x"].tolist(), float), got["y"].to_numpy(float)
    order = np.lexsort((y, *x.T))  # the fit does not depend on the order of arrival
    return AdditiveModel().fit(x[order], y[order])


def score_quality(docs: DataFrame, model: AdditiveModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(``id_col``, held_out, score, predicted) for every row; null and empty texts too."""
    limit_batches(docs.sparkSession)
    held = docs.sparkSession.sparkContext.broadcast(model)

    @released
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.array([features(t) for t in batch.column(2).to_pylist()], float).reshape(-1, len(FEATURES))
            s = held.value.score(x)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(s), pa.array((s >= 0.5).astype(np.int32))], names=["id", "held_out", "score", "predicted"])

    kind = docs.schema[id_col].dataType.simpleString()
    rows = spread(docs.select(id_col, text_col)).select(F.col(id_col).alias("id"), held_out(id_col).alias("held_out"), F.col(text_col).cast("binary").alias("body"))
    return rows.mapInArrow(run, f"id {kind}, held_out boolean, score double, predicted int").withColumnRenamed("id", id_col)


def op10_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    return score_quality(docs, fit_quality(docs, labels))
