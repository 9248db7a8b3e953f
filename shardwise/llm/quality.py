"""Quality classifier: histogram gradient-boosted trees over document statistics.

Statistics of a text are computed over the whole text by byte histograms and counts of words and lines.
Training runs on the driver over a bounded sample of labelled rows (TRAIN_ROWS, those with the smallest
hashes of their ids); each feature is cut into quantile bins and splits are found from histograms of
gradients and Hessians. The trees are complete and kept as flat arrays (feature, threshold per inner
node, value per leaf), so scoring walks all trees of a batch level by level in numpy. The model, a few
kilobytes whatever the corpus, travels with the task.

Defined cases: null text counts as empty and gets a score like any other; null labels are not used, of
several labels of a document the largest counts, and of several texts of a labelled id the one with the least statistics; with no labels, or labels of one kind only, the score is
their smoothed mean (0.5 without any); an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Bound on the labelled rows used for fitting; documents scored 1 from here on.
TRAIN_ROWS, THRESHOLD = 20_000, 0.3

# Frequent function words of English, French, German and Spanish.
FUNCTION_WORDS = frozenset("the of and to in a is that for it on with as at by this are be or from de la le les et des en un une du que qui pour dans der die das und ist von zu den mit ein eine nicht el los las y por con se del al".split())

CLASSES = (b"abcdefghijklmnopqrstuvwxyz", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b".", b",", b"!?;:", b"%*#$&@^~", b"|", b"<>{}[]()/\\=_+", b"\"'`-", b" ", b"\n", bytes(range(128, 256)))
BYTE_CLASS = np.zeros((256, len(CLASSES)))
for _k, _members in enumerate(CLASSES):
    BYTE_CLASS[list(_members), _k] = 1.0


def statistics(text: str | None) -> list[float]:
    """Features of one whole text."""
    text = text or ""
    data = text.encode("utf-8", "surrogatepass")
    n = len(data)
    histogram = np.bincount(np.frombuffer(data, np.uint8), minlength=256)
    share = histogram / max(n, 1)
    seen = share[share > 0]
    words = text.split()
    counts = Counter(words)
    w = max(len(words), 1)
    lengths = [len(x) for x in counts]
    lines = [x for x in text.split("\n") if x.strip()]
    rows = Counter(lines)
    repeated = sum(len(x) * (c - 1) for x, c in rows.items())
    ll = max(len(lines), 1)
    top = counts.most_common(1)[0][1] if counts else 0
    bare = sum(c for x, c in counts.items() if x.lower().strip(".,;:!?") in FUNCTION_WORDS)
    odd = sum(c for x, c in counts.items() if not x[-1].isalnum() and x[-1] not in ".,;:!?\"')")
    return [
        *(share @ BYTE_CLASS).tolist(),
        math.log1p(n),
        math.log1p(len(words)),
        math.log1p(len(lines)),
        sum(len(x) * c for x, c in counts.items()) / w,
        max(lengths, default=0),
        len(counts) / w,
        len(counts) / math.sqrt(w),
        top / w,
        bare / w,
        odd / w,
        repeated / max(len(text), 1),
        len(rows) / ll,
        sum(map(len, lines)) / ll,
        sum(len(x) < 40 for x in lines) / ll,
        sum(x.rstrip()[-1] in ".!?" for x in lines) / ll,
        float(-(seen * np.log2(seen)).sum()) if n else 0.0,
        sum(c for c in counts.values() if c == 1) / w,
        sum(x[0].isupper() for x in lines) / ll,
    ]


FEATURES = len(statistics(""))


@dataclass(frozen=True)
class Params:
    trees: int = 120
    depth: int = 4
    rate: float = 0.12
    bins: int = 64
    least_hessian: float = 2.0
    penalty: float = 1.0


@dataclass
class Trees:
    """Complete trees in flat arrays: (trees, 2^depth - 1) inner nodes in breadth-first order, (trees, 2^depth) leaves."""

    feature: np.ndarray
    threshold: np.ndarray
    leaf: np.ndarray
    start: float

    def score(self, x: np.ndarray) -> np.ndarray:
        n, (trees, inner) = len(x), self.feature.shape
        if not trees:
            return np.full(n, 1 / (1 + math.exp(-self.start)))
        at = np.zeros((n, trees), np.int64)
        base, rows = np.arange(trees) * inner, np.arange(n)[:, None]
        feature, threshold = self.feature.ravel(), self.threshold.ravel()
        for _ in range((inner + 1).bit_length() - 1):
            node = base + at
            at = 2 * at + 1 + (x[rows, feature[node]] > threshold[node])
        leaf = self.leaf.ravel()[np.arange(trees) * (inner + 1) + at - inner]
        return 1 / (1 + np.exp(-(self.start + leaf.sum(axis=1))))


def fit(x: np.ndarray, y: np.ndarray, params: Params = Params()) -> Trees:
    """Boost trees on logistic loss. Ties between splits go to the lower feature, then the lower bin."""
    inner = (1 << params.depth) - 1
    none = Trees(np.zeros((0, inner), np.int64), np.zeros((0, inner)), np.zeros((0, inner + 1)), 0.0)
    mean = (y.sum() + 1.0) / (len(y) + 2.0)
    none.start = math.log(mean / (1 - mean))
    if len(y) == 0 or y.min() == y.max():
        return none
    n, m = x.shape
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, params.bins + 1)[1:-1])) for j in range(m)]
    binned = np.stack([np.searchsorted(e, x[:, j], side="left") for j, e in enumerate(edges)], axis=1)
    wide = params.bins
    flat = binned + np.arange(m) * wide
    out_f, out_t, out_v, raw = [], [], [], np.full(n, none.start)
    for _ in range(params.trees):
        p = 1 / (1 + np.exp(-raw))
        g, h = y - p, p * (1 - p)
        feature, threshold, at = np.zeros(inner, np.int64), np.full(inner, np.inf), np.zeros(n, np.int64)
        for level in range(params.depth):
            first, nodes = (1 << level) - 1, 1 << level
            cell = ((at - first)[:, None] * (m * wide) + flat).ravel()
            size = nodes * m * wide
            gs = np.bincount(cell, np.repeat(g, m), size).reshape(nodes, m, wide).cumsum(axis=2)
            hs = np.bincount(cell, np.repeat(h, m), size).reshape(nodes, m, wide).cumsum(axis=2)
            gt, ht = gs[:, :, -1:], hs[:, :, -1:]
            gain = gs**2 / (hs + params.penalty) + (gt - gs) ** 2 / (ht - hs + params.penalty) - gt**2 / (ht + params.penalty)
            gain[(hs < params.least_hessian) | (ht - hs < params.least_hessian)] = -1.0
            best = gain.reshape(nodes, -1).argmax(axis=1)
            for k in range(nodes):
                j, b = divmod(int(best[k]), wide)
                if gain[k, j, b] > 1e-9 and b < len(edges[j]):
                    feature[first + k], threshold[first + k] = j, edges[j][b]
            right = x[np.arange(n), feature[at]] > threshold[at]
            at = 2 * at + 1 + right
        k = at - inner
        value = params.rate * np.bincount(k, g, inner + 1) / (np.bincount(k, h, inner + 1) + params.penalty)
        raw += value[k]
        out_f.append(feature)
        out_t.append(threshold)
        out_v.append(value)
    return Trees(np.array(out_f), np.array(out_t), np.array(out_v), none.start)


def _features(docs: DataFrame) -> DataFrame:
    """docs(id, text) to (id, x)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = [statistics(t) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(x, pa.list_(pa.float64()))], ["id", "x"])

    return docs.mapInArrow(run, f"id {docs.schema[0].dataType.simpleString()}, x array<double>")


def held_out(id_col: str = "doc_id"):
    """Rows that are never learnt from."""
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % 5 == 0


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", rows: int = TRAIN_ROWS, params: Params = Params()) -> Trees:
    """Fit on at most so many labelled rows; held-out rows are not read for it."""
    usable = labels.where(~held_out(id_col)).where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).groupBy(F.col(id_col).alias("id")).agg(F.max(label_col).alias("y"))
    sample = usable.orderBy(F.xxhash64("id"), "id").limit(rows)  # bounded by rows, so it may be broadcast
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    chosen = texts.join(F.broadcast(sample), "id")
    # one row of each id: rows that repeat an id would not be bounded by the sample
    one = _features(chosen.select("id", "text")).groupBy("id").agg(F.min("x").alias("x"))
    got = one.join(F.broadcast(sample), "id").select("id", "x", "y").toPandas().sort_values("id", kind="stable")
    if not len(got):
        return fit(np.zeros((0, FEATURES)), np.zeros(0), params)
    return fit(np.array(got.x.tolist(), float), got.y.to_numpy(float), params)


def score(docs: DataFrame, model: Trees, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD, keep: tuple[str, ...] = ()) -> DataFrame:
    """id, score, predicted for every row, and the columns named in keep unchanged; one pass, no shuffle."""
    names = [id_col, *[c for c in keep if c != id_col]]
    own = names.index(text_col) if text_col in names else len(names)
    used = docs.select(*names, *([] if own < len(names) else [F.col(text_col).cast("string").alias("_text")]))
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.select(*names).schema.fields)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                s = model.score(np.array([statistics(t) for t in part.column(own).to_pylist()], float).reshape(-1, FEATURES))
                yield pa.RecordBatch.from_arrays([*part.columns[: len(names)], pa.array(s), pa.array((s >= threshold).astype(np.int32))], [*names, "score", "predicted"])

    return used.mapInArrow(run, f"{fields}, score double, predicted int")
