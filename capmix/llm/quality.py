"""Quality classifier: histogram gradient-boosted trees over document statistics.

Statistics of the whole text (lengths, shares of character classes, repetition of words and lines) feed
trees that are grown on binned features by gradient histograms, and flattened into arrays of features,
thresholds, children and values, which numpy walks for a whole batch at once.

The model is fitted on the driver from at most `sample_rows` labelled rows outside the hold-out (numbers,
not texts, are fetched); it is a few KB and is sent to every task.

Defined cases: null and empty texts have all statistics zero and get a score like any other; without
training rows of both labels the score is the share of label 1 (about 0 without rows); repeated rows get equal
scores; a column of documents with the name of a result is replaced; empty tables work.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import small
from .labelled import remainder, training_rows

MODULUS, HELD_OUT, SAMPLE_ROWS = 3, 1, 20_000
ADDED = ("score", "predicted")

STATISTICS = (
    "bytes", "words", "word_bytes", "longest_word", "distinct_words", "commonest_word", "lines", "line_bytes", "distinct_lines", "commonest_line",
    "upper", "lower", "digits", "beyond_ascii", "spaces", "commas", "stops", "exclamations", "bars", "signs", "brackets", "slashes_colons", "capital_words", "signed_words", "links",
)


def statistics(text: bytes | None) -> list[float]:
    """STATISTICS of one whole text, in their order."""
    if not text:
        return [0.0] * len(STATISTICS)
    n = len(text)
    c = np.bincount(np.frombuffer(text, np.uint8), minlength=256)
    share = lambda *codes: float(c[list(codes)].sum()) / n
    words = text.split()
    k = max(len(words), 1)
    counts: dict[bytes, int] = {}
    for w in words:
        counts[w] = counts.get(w, 0) + 1
    lines = [x for x in text.split(b"\n") if x.strip()]
    by_line: dict[bytes, int] = {}
    for x in lines:
        by_line[x] = by_line.get(x, 0) + 1
    m = max(len(lines), 1)
    return [
        float(np.log1p(n)), float(np.log1p(len(words))), (n - float(c[[32, 10, 9, 13]].sum())) / k, float(np.log1p(max(map(len, words), default=0))), len(counts) / k, max(counts.values(), default=0) / k,
        float(np.log1p(len(lines))), float(np.log1p(n / m)), len(by_line) / m, max(by_line.values(), default=0) / m,
        float(c[65:91].sum()) / n, float(c[97:123].sum()) / n, float(c[48:58].sum()) / n, float(c[128:].sum()) / n, share(32, 9, 10, 13), share(44), share(46), share(33), share(124), share(35, 36, 37, 38, 42, 64, 94, 126), share(40, 41, 60, 62, 91, 93, 123, 125), share(47, 58),
        sum(map(bytes.isupper, words)) / k, sum(w[-1] not in b".,;:" and w[-1] < 128 and not w[-1:].isalnum() for w in words) / k, text.count(b"http") / k,
    ]


@dataclass
class Trees:
    """Flattened trees: node arrays, and the root of each tree. A leaf has left == itself."""

    feature: np.ndarray
    threshold: np.ndarray
    left: np.ndarray
    right: np.ndarray
    value: np.ndarray
    roots: np.ndarray
    depth: int
    bias: float

    def score(self, x: np.ndarray) -> np.ndarray:
        """Probabilities of label 1 for the rows of x."""
        raw = np.full(len(x), self.bias)
        rows = np.arange(len(x))
        for root in self.roots.tolist():
            at = np.full(len(x), root)
            for _ in range(self.depth):
                at = np.where(x[rows, self.feature[at]] <= self.threshold[at], self.left[at], self.right[at])
            raw += self.value[at]
        return 1 / (1 + np.exp(-np.clip(raw, -30, 30)))


def fit_trees(x: np.ndarray, y: np.ndarray, rounds: int = 80, depth: int = 4, rate: float = 0.15, bins: int = 64, ridge: float = 1.0, min_rows: int = 8) -> Trees:
    """Gradient boosting on the logistic loss, level by level over feature histograms."""
    n, d = x.shape if x.ndim == 2 else (0, len(STATISTICS))
    p0 = float(y.mean()) if n else 0.0
    bias = float(np.log(max(p0, 1e-9) / max(1 - p0, 1e-9)))
    nodes: list[list[float]] = []
    roots = []
    if n and 0 < p0 < 1:
        edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1])) for f in range(d)]
        binned = np.stack([np.searchsorted(edges[f], x[:, f], side="left") for f in range(d)])
        raw = np.full(n, bias)
        for _ in range(rounds):
            p = 1 / (1 + np.exp(-np.clip(raw, -30, 30)))
            g, h = y - p, np.maximum(p * (1 - p), 1e-12)
            roots.append(len(nodes))
            nodes.append([0, np.inf, len(nodes), len(nodes), 0.0])
            where, open_nodes = np.full(n, roots[-1]), [roots[-1]]
            for level in range(depth + 1):
                slot = {v: k for k, v in enumerate(open_nodes)}
                lookup = np.full(len(nodes), -1)
                lookup[open_nodes] = range(len(open_nodes))
                own = lookup[where]
                live = own >= 0
                m = len(open_nodes)
                gs, hs = np.bincount(own[live], g[live], m), np.bincount(own[live], h[live], m)
                for v, k in slot.items():
                    nodes[v][4] = rate * gs[k] / (hs[k] + ridge)
                if level == depth:
                    break
                best = [(1e-6, -1, 0)] * m
                for f in range(d):
                    if not len(edges[f]):
                        continue
                    key = own[live] * (bins + 1) + binned[f][live]
                    size = m * (bins + 1)
                    gh, hh, ch = (np.bincount(key, w, size).reshape(m, -1).cumsum(axis=1)[:, :-1] for w in (g[live], h[live], None))
                    gain = gh**2 / (hh + ridge) + (gs[:, None] - gh) ** 2 / (hs[:, None] - hh + ridge) - (gs**2 / (hs + ridge))[:, None]
                    total = np.bincount(own[live], minlength=m)[:, None]
                    gain[(ch < min_rows) | (total - ch < min_rows)] = -1
                    gain = gain[:, : len(edges[f])]
                    at = gain.argmax(axis=1)
                    for k in range(m):
                        if gain[k, at[k]] > best[k][0]:
                            best[k] = (float(gain[k, at[k]]), f, int(at[k]))
                grown = []
                for v, k in slot.items():
                    _, f, at = best[k]
                    if f < 0:
                        continue
                    a, b = len(nodes), len(nodes) + 1
                    nodes.append([0, np.inf, a, a, 0.0])
                    nodes.append([0, np.inf, b, b, 0.0])
                    nodes[v][:4] = [f, float(edges[f][at]), a, b]
                    mine = np.flatnonzero(where == v)
                    where[mine] = np.where(binned[f][mine] <= at, a, b)
                    grown += [a, b]
                open_nodes = grown
                if not grown:
                    break
            raw += np.array([v[4] for v in nodes])[where]
    cols = list(zip(*nodes, strict=True)) if nodes else [[]] * 5
    return Trees(*(np.array(c, t) for c, t in zip(cols, (np.int64, float, np.int64, np.int64, float), strict=True)), np.array(roots, np.int64), depth, bias)


def train(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS, modulus: int = MODULUS, held_out: int = HELD_OUT, id_col: str = "doc_id", text_col: str = "text", label: str = "quality", **options) -> Trees:
    """Fit on at most `sample_rows` labelled rows whose id is not held out."""

    def measure(batches):
        for batch in small(batches):
            yield pa.RecordBatch.from_arrays([pa.array([statistics(t) for t in batch.column(0).to_pylist()], pa.list_(pa.float64())), batch.column(1)], ["x", "y"])

    rows = training_rows(docs, labels, label, modulus, held_out, sample_rows, id_col, text_col).mapInArrow(measure, "x array<double>, y int").toArrow()
    # the order of the rows must not matter to the model
    x = np.array(rows.column("x").to_pylist(), float).reshape(-1, len(STATISTICS))
    y = (rows.column("y").to_numpy() != 0).astype(float)
    order = np.lexsort((y, *x.T[::-1]))
    return fit_trees(x[order], y[order], **options)


def score_quality(docs: DataFrame, trees: Trees, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Add score double and predicted int to docs; `keep` names the columns to carry (all)."""
    keep = [c for c in (docs.columns if keep is None else keep) if c not in ADDED]
    source = text_col if text_col in keep else "_text"
    rows = docs.select(*keep, *([] if source in keep else [F.col(text_col).alias("_text")]))

    def work(batches):
        for batch in small(batches):
            x = np.array([statistics(t) for t in batch.column(source).cast(pa.binary()).to_pylist()], float).reshape(-1, len(STATISTICS))
            scores = trees.score(x)
            table = {n: batch.column(n) for n in keep} | {"score": pa.array(scores), "predicted": pa.array((scores >= 0.5).astype(np.int32))}
            yield pa.RecordBatch.from_arrays(list(table.values()), list(table))

    return rows.mapInArrow(work, T.StructType([*rows.select(*keep).schema, T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())]))


def held_out_column(id_col: str = "doc_id", modulus: int = MODULUS, held_out: int = HELD_OUT):
    return remainder(id_col, modulus) == held_out
