"""Quality classifier: a generalised additive model with pairwise interactions."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .blocks import flat
from .common import free_name

THRESHOLD = 0.7
MAX_LABELLED = 20_000

FEATURES = [
    "log_bytes", "log_words", "upper", "digits", "exclaim", "question", "pipe", "symbols", "stops", "commas", "blanks",
    "lines", "foreign", "entropy", "word_length", "short_words", "long_words", "distinct", "repeats", "line_repeats",
    "shouted", "line_length",
]


def _mask(chars: bytes) -> np.ndarray:
    out = np.zeros(256)
    out[list(chars)] = 1
    return out


_UPPER, _LOWER = _mask(bytes(range(65, 91))), _mask(bytes(range(97, 123)))
_DIGIT, _BLANK = _mask(b"0123456789"), _mask(b" \t\n\r\x0b\x0c")
_SYMBOL, _FOREIGN = _mask(b"#$%&*@^~<>{}[]\\=+_"), _mask(bytes(range(128, 256)))
_CLASSES = np.stack([_UPPER, _LOWER, _DIGIT, _BLANK, _SYMBOL, _FOREIGN, _mask(b"!"), _mask(b"?"), _mask(b"|"), _mask(b"."), _mask(b","), _mask(b"\n")])


def features(body: bytes) -> list[float]:
    """Feature values of a whole text; all are 0 for an empty one."""
    n = len(body)
    if n == 0:
        return [0.0] * len(FEATURES)
    counts = np.zeros(256, np.int64)
    data = np.frombuffer(body, np.uint8)
    for at in range(0, n, 1 << 20):
        counts += np.bincount(data[at : at + (1 << 20)], minlength=256)
    upper, lower, digit, blank, symbol, foreign, exclaim, question, pipe, stop, comma, line = (_CLASSES @ counts).tolist()
    p = counts[counts > 0] / n
    words = body.split()
    k = max(1, len(words))
    lengths = list(map(len, words))
    rows = body.split(b"\n")
    return [
        math.log1p(n), math.log1p(len(words)), upper / max(1.0, upper + lower), digit / n, exclaim / n, question / n, pipe / n,
        symbol / n, stop / n, comma / n, blank / n, line / n, foreign / n, float(-(p * np.log2(p)).sum()),
        sum(lengths) / k, sum(x < 3 for x in lengths) / k, sum(x > 14 for x in lengths) / k,
        len(set(words)) / k, sum(map(eq, words, words[1:])) / k, 1 - len(set(rows)) / len(rows),
        sum(w.isupper() for w in words) / k, math.log1p(n / len(rows)),
    ]


@dataclass
class Additive:
    """logit = base + a table entry for each feature's bin + one for each pair's bins."""

    base: float = math.inf
    cuts: list[np.ndarray] = field(default_factory=list)
    tables: list[np.ndarray] = field(default_factory=list)
    pairs: list[tuple[int, int]] = field(default_factory=list)
    pair_cuts: list[np.ndarray] = field(default_factory=list)
    pair_tables: list[np.ndarray] = field(default_factory=list)

    def score(self, x: np.ndarray) -> np.ndarray:
        """Probability of label 1 for rows of feature values."""
        z = np.full(len(x), self.base)
        for f, (cuts, table) in enumerate(zip(self.cuts, self.tables)):
            z += table[np.searchsorted(cuts, x[:, f], "right")]
        coarse = [np.searchsorted(c, x[:, f], "right") for f, c in enumerate(self.pair_cuts)]
        for (a, b), table in zip(self.pairs, self.pair_tables):
            z += table[coarse[a], coarse[b]]
        return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def _cuts(x: np.ndarray, bins: int) -> np.ndarray:
    """Cut points between distinct values, near quantiles."""
    at = np.unique(np.quantile(x, np.linspace(0, 1, bins + 1)[1:-1]))
    values = np.unique(x)
    return (at + values[np.minimum(np.searchsorted(values, at, "right"), len(values) - 1)]) / 2 if len(at) else at


def _gain(g: np.ndarray, h: np.ndarray, reg: float) -> np.ndarray:
    return g * g / (h + reg)


def _tree(g: np.ndarray, h: np.ndarray, leaves: int, reg: float) -> np.ndarray:
    """Newton steps of a shallow tree over the ordered bins of one feature."""
    parts = [(0, len(g))]
    cg, ch = np.concatenate([[0], np.cumsum(g)]), np.concatenate([[0], np.cumsum(h)])
    while len(parts) < leaves:
        best = (1e-9, None, None)
        for i, (a, b) in enumerate(parts):
            if b - a < 2:
                continue
            gl, hl = cg[a + 1 : b] - cg[a], ch[a + 1 : b] - ch[a]
            gt, ht = cg[b] - cg[a], ch[b] - ch[a]
            gain = _gain(gl, hl, reg) + _gain(gt - gl, ht - hl, reg) - _gain(gt, ht, reg)
            k = int(gain.argmax())
            if gain[k] > best[0]:
                best = (gain[k], i, a + 1 + k)
        if best[1] is None:
            break
        a, b = parts.pop(best[1])
        parts += [(a, best[2]), (best[2], b)]
    out = np.zeros(len(g))
    for a, b in parts:
        out[a:b] = -(cg[b] - cg[a]) / (ch[b] - ch[a] + reg)
    return out


def _quadrants(g: np.ndarray, h: np.ndarray, reg: float) -> tuple[float, np.ndarray]:
    """(gain, steps) of the best tree that cuts a grid of two features into four."""
    cg, ch = g.cumsum(0).cumsum(1), h.cumsum(0).cumsum(1)
    gt, ht = cg[-1, -1], ch[-1, -1]
    if min(g.shape) < 2:
        return 0.0, np.zeros_like(g)
    q = []
    for c, t in ((cg, gt), (ch, ht)):
        ll = c[:-1, :-1]
        lr, rl = c[:-1, -1:] - ll, c[-1:, :-1] - ll
        q.append((ll, lr, rl, t - ll - lr - rl))
    gain = sum(_gain(a, b, reg) for a, b in zip(*q)) - _gain(gt, ht, reg)
    i, j = np.unravel_index(int(gain.argmax()), gain.shape)
    steps = np.empty_like(g)
    for k, (rows, cols) in enumerate(((slice(0, i + 1), slice(0, j + 1)), (slice(0, i + 1), slice(j + 1, None)), (slice(i + 1, None), slice(0, j + 1)), (slice(i + 1, None), slice(j + 1, None)))):
        steps[rows, cols] = -q[0][k][i, j] / (q[1][k][i, j] + reg)
    return float(gain[i, j]), steps


def fit(
    x: np.ndarray, y: np.ndarray, rounds: int = 150, pair_rounds: int = 40, pairs: int = 10, rate: float = 0.15,
    bins: int = 48, coarse: int = 12, leaves: int = 4, reg: float = 2.0,
) -> Additive:
    """Cyclic boosting: each round gives every feature in turn one shallow tree.

    The trees of a feature add up to its lookup table.  Then the pairs with
    the largest gain on what is left are boosted in the same way with trees
    over two features.  Without rows nothing speaks against a document and
    every score is 1; with one label only the base rate counts.
    """
    if len(y) == 0:
        return Additive()
    rate_1 = (y.sum() + 0.5) / (len(y) + 1)
    model = Additive(float(np.log(rate_1 / (1 - rate_1))))
    n = x.shape[1]
    model.cuts = [_cuts(x[:, f], bins) for f in range(n)]
    model.pair_cuts = [_cuts(x[:, f], coarse) for f in range(n)]
    model.tables = [np.zeros(len(c) + 1) for c in model.cuts]
    binned = [np.searchsorted(c, x[:, f], "right") for f, c in enumerate(model.cuts)]
    z = np.full(len(y), model.base)
    for _ in range(rounds):
        for f in range(n):
            p = 1 / (1 + np.exp(-z))
            size = len(model.tables[f])
            g, h = np.bincount(binned[f], p - y, size), np.bincount(binned[f], p * (1 - p), size)
            step = rate * _tree(g, h, leaves, reg)
            model.tables[f] += step
            z += step[binned[f]]
    grid = [np.searchsorted(c, x[:, f], "right") for f, c in enumerate(model.pair_cuts)]
    wide = [len(c) + 1 for c in model.pair_cuts]

    def hist(a: int, b: int, w: np.ndarray) -> np.ndarray:
        return np.bincount(grid[a] * wide[b] + grid[b], w, wide[a] * wide[b]).reshape(wide[a], wide[b])

    p = 1 / (1 + np.exp(-z))
    gains = sorted(
        ((-_quadrants(hist(a, b, p - y), hist(a, b, p * (1 - p)), reg)[0], a, b) for a in range(n) for b in range(a + 1, n))
    )
    model.pairs = [(a, b) for _, a, b in gains[:pairs]]
    model.pair_tables = [np.zeros((wide[a], wide[b])) for a, b in model.pairs]
    for _ in range(pair_rounds):
        for k, (a, b) in enumerate(model.pairs):
            p = 1 / (1 + np.exp(-z))
            step = rate * _quadrants(hist(a, b, p - y), hist(a, b, p * (1 - p)), reg)[1]
            model.pair_tables[k] += step
            z += step[grid[a], grid[b]]
    return model


def _rows(column: pa.Array) -> np.ndarray:
    offsets, data = flat(column)
    at = offsets.tolist()
    out = [features(data[a:b].tobytes()) for a, b in zip(at, at[1:])]
    return np.array(out, float).reshape(len(out), len(FEATURES))


def fold(doc_id: str, parts: int) -> Column:
    """crc32 of the id as text, modulo ``parts``; null for a null id."""
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % parts


def train(
    docs: DataFrame, labels: DataFrame, text: str = "text", doc_id: str = "doc_id", label: str = "quality",
    max_labelled: int = MAX_LABELLED,
) -> Additive:
    """Fit the model on the labelled rows of ``docs``.

    At most ``max_labelled`` labels are used, those with the smallest hash of
    their id, and at most twice as many rows with these ids, by the same hash;
    this bounds what the driver gathers.  Rows with a null id or label teach
    nothing; rows with one id and the same features count once.
    """
    chosen = (
        labels.where(F.col(doc_id).isNotNull() & F.col(label).isNotNull())
        .select(F.col(doc_id).alias("_id"), (F.col(label) > 0).cast("double").alias("_y"))
        .orderBy(F.xxhash64("_id"), "_id", "_y")
        .limit(max_labelled)
    )
    rows = docs.select(F.col(doc_id).alias("_id"), F.col(text).cast("string").alias("_text"))
    rows = rows.join(F.broadcast(chosen), "_id").select("_id", "_text", "_y")
    kind = rows.schema["_id"].dataType.simpleString()

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = _rows(batch.column("_text"))
            flat_x = pa.array(np.column_stack([x, np.asarray(batch.column("_y"), float)]).ravel())
            ends = np.arange(0, len(flat_x) + 1, len(FEATURES) + 1, dtype=np.int32)
            yield pa.RecordBatch.from_arrays([batch.column("_id"), pa.ListArray.from_arrays(pa.array(ends), flat_x)], ["_id", "v"])

    made = rows.mapInArrow(work, f"_id {kind}, v array<double>").dropDuplicates()
    made = made.orderBy(F.xxhash64("_id"), "_id", "v").limit(2 * max_labelled).select("v")
    got = np.array([r[0] for r in made.collect()], float).reshape(-1, len(FEATURES) + 1)
    got = got[np.lexsort(got.T)]
    return fit(got[:, :-1], got[:, -1])


def score(docs: DataFrame, model: Additive, text: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """Every row of ``docs`` with score and predicted (columns of these names are replaced).

    Bins are looked up and table entries added for whole batches at a time.
    Null counts as the empty text, which is scored like any other.  One pass,
    no shuffle.
    """
    held = docs.drop(*[c for c in docs.columns if c.lower() in ("score", "predicted") and c != text])
    name = text
    if text in ("score", "predicted"):
        name = free_name(held.columns, "_text")
        held = held.withColumnRenamed(text, name)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in held.schema.fields)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            p = model.score(_rows(batch.column(name)))
            yield pa.RecordBatch.from_arrays(
                [*batch.columns, pa.array(p, pa.float64()), pa.array((p >= threshold).astype(np.int32), pa.int32())],
                [*batch.schema.names, "score", "predicted"],
            )

    out = held.mapInArrow(work, schema + ", score double, predicted int")
    return out.drop(name) if name != text else out
