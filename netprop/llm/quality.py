"""Quality rules: counted base rules, then gradient-boosted trees over document statistics.

The trees are grown here from labelled rows (second-order boosting of the
logistic loss over binned features), with monotonic constraints on chosen
statistics: where more of something can only lower (or raise) quality, a split on
it may not order its sides the other way, and the bound between two sides holds
for everything below them. A fitted model is a handful of flat numpy arrays; all
rows of a batch walk down all trees together.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
#: Statistic and its constraint: -1 more is never better, 1 never worse, 0 free.
FEATURES = (
    ("log_words", 0), ("mean_word", 0), ("symbol_share", -1), ("dup_line_share", -1), ("repeat_share", -1), ("upper_share", 0), ("digit_share", 0),
    ("punctuation_share", 0), ("distinct_words", 0), ("log_lines", 0), ("words_per_line", 0), ("bang_share", -1), ("wide_share", 0), ("longest_word", 0), ("line_end_share", 0),
)
#: Labelled rows that a model is fitted on at most: those of smallest hashed id.
SAMPLE_ROWS = 20_000

_SPACE = np.array([9, 10, 11, 12, 13, 32])
_SYMBOLS = np.frombuffer(b"#*$%&|<>", np.uint8)
_MARKS = np.frombuffer(b".,;:?'\"()-", np.uint8)


def statistics(text: bytes | None) -> tuple[tuple[int, ...], list[float]]:
    """Base counts (in the order of BASE) and features (in that of FEATURES) of one UTF-8 text."""
    text = text or b""
    seen = np.bincount(np.frombuffer(text, np.uint8), minlength=256)
    points = int(seen.sum() - seen[0x80:0xC0].sum())
    letters = points - int(seen[_SPACE].sum())
    symbols = int(seen[_SYMBOLS].sum())
    words = text.split()
    n = len(words)
    lines = [x for x in text.split(b"\n") if x and not x.isspace()]
    dup = len(lines) - len(set(lines))
    names: dict[bytes, int] = {}
    ids = np.fromiter((names.setdefault(w, len(names)) for w in words), np.int64, n)
    repeat = repeated_words(ids, len(names))
    share = lambda x: x / max(letters, 1)
    ends = sum(x.rstrip().endswith((b".", b"?", b"!", b'"')) for x in lines)
    return (n, letters, symbols, dup, repeat), [
        np.log1p(n), share(n) and letters / n, share(symbols), dup / max(len(lines), 1), repeat / max(n, 1), share(int(seen[65:91].sum())), share(int(seen[48:58].sum())),
        share(int(seen[_MARKS].sum())), len(names) / max(n, 1), np.log1p(len(lines)), n / max(len(lines), 1), share(int(seen[33])), share(int(seen[0xC0:].sum())), max(map(len, words), default=0), ends / max(len(lines), 1),
    ]


def repeated_words(ids: np.ndarray, kinds: int) -> int:
    """Words that stand in some three-word window which occurs twice or more."""
    if len(ids) < 4:
        return 0
    if kinds < 1 << 20:
        window = (ids[:-2] * kinds + ids[1:-1]) * kinds + ids[2:]
    else:
        _, pair = np.unique(ids[:-1] * kinds + ids[1:], return_inverse=True)
        window = pair[:-1] * kinds + ids[2:]
    order = np.argsort(window, kind="stable")
    alike = window[order[1:]] == window[order[:-1]]
    twice = np.zeros(len(window), bool)
    twice[order[1:][alike]] = True
    twice[order[:-1][alike]] = True
    covered = np.zeros(len(ids), bool)
    for k in range(3):
        covered[k : k + len(twice)] |= twice
    return int(covered.sum())


def base_failed(base: np.ndarray) -> np.ndarray:
    """Rows of BASE counts: fewer than 50 words, or over half of them in repeated windows."""
    return (base[:, 0] < 50) | (100 * base[:, 4] > 50 * base[:, 0])


# ----------------------------------------------------------------------- trees


@dataclass
class Trees:
    """All trees as arrays of shape (trees, nodes); node i has children 2i + 1 and 2i + 2; feature -1 marks a leaf."""

    feature: np.ndarray
    threshold: np.ndarray
    value: np.ndarray
    start: float
    depth: int

    def margin(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.start)
        rows = np.arange(len(x))
        for f, t, v in zip(self.feature, self.threshold, self.value, strict=True):
            at = np.zeros(len(x), np.int64)
            for _ in range(self.depth):
                split = f[at]
                down = 2 * at + 1 + (x[rows, split] > t[at])
                at = np.where(split < 0, at, down)
            out += v[at]
        return out

    def score(self, x: np.ndarray) -> np.ndarray:
        """Chance of good quality."""
        return 1.0 / (1.0 + np.exp(-self.margin(x)))


def fit(x: np.ndarray, y: np.ndarray, monotone: tuple[int, ...], trees: int = 60, depth: int = 4, rate: float = 0.15, bins: int = 64, ridge: float = 1.0, least: float = 5.0) -> Trees:
    """Boosted trees of the labels ``y`` (0 or 1). Without rows, or with one class, no tree is grown."""
    nodes = (1 << (depth + 1)) - 1
    share = min(max(float(y.mean()) if len(y) else 0.5, 1e-6), 1 - 1e-6)
    start = float(np.log(share / (1 - share)))
    if len(y) == 0 or y.min() == y.max():
        return Trees(np.zeros((0, nodes), np.int64), np.zeros((0, nodes)), np.zeros((0, nodes)), start, depth)
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1], method="lower")) for j in range(x.shape[1])]
    binned = np.stack([np.searchsorted(e, x[:, j], side="left") for j, e in enumerate(edges)], axis=1)
    wide = max(len(e) for e in edges) + 1
    sign = np.array(monotone, float)
    margin = np.full(len(y), start)
    grown = []
    for _ in range(trees):
        p = 1 / (1 + np.exp(-margin))
        g, h = p - y, p * (1 - p)
        feature, threshold, value = np.full(nodes, -1), np.zeros(nodes), np.zeros(nodes)
        low, high = np.full(nodes, -np.inf), np.full(nodes, np.inf)
        at = np.zeros(len(y), np.int64)
        value[0] = -g.sum() / (h.sum() + ridge)
        for level in range(depth):
            first, count = (1 << level) - 1, 1 << level
            live = at >= first
            cell = (at[live] - first)[:, None] * x.shape[1] + np.arange(x.shape[1])
            spot = (cell * wide + binned[live]).ravel()
            shape = (count, x.shape[1], wide)
            gs, hs = (np.bincount(spot, np.repeat(w[live], x.shape[1]), minlength=np.prod(shape)).reshape(shape).cumsum(2) for w in (g, h))
            ga, ha = gs[:, :, -1:], hs[:, :, -1:]
            bound = slice(first, first + count)
            clip = lambda v, b=bound: np.clip(v, low[b, None, None], high[b, None, None])  # noqa: B023, E731
            vl, vr = clip(-gs / (hs + ridge)), clip(-(ga - gs) / (ha - hs + ridge))
            gain = lambda v, a, b: -(a * v + 0.5 * (b + ridge) * v * v)
            score = gain(vl, gs, hs) + gain(vr, ga - gs, ha - hs) - gain(clip(-ga / (ha + ridge)), ga, ha)
            score[(hs < least) | (ha - hs < least) | (sign[:, None] * (vr - vl) < 0)] = -np.inf
            best = score.reshape(count, -1).argmax(1)
            for k in np.flatnonzero(score.reshape(count, -1).max(1) > 1e-6):
                j, b = divmod(int(best[k]), wide)
                if b >= len(edges[j]):
                    continue
                node = first + int(k)
                feature[node], threshold[node] = j, edges[j][b]
                l, r = 2 * node + 1, 2 * node + 2
                value[l], value[r] = vl[k, j, b], vr[k, j, b]
                low[l], high[l], low[r], high[r] = low[node], high[node], low[node], high[node]
                middle = (value[l] + value[r]) / 2
                if sign[j] > 0:
                    high[l] = low[r] = middle
                elif sign[j] < 0:
                    low[l] = high[r] = middle
            split = feature[at]
            rows = np.flatnonzero(live & (split >= 0))
            at[rows] = 2 * at[rows] + 1 + (x[rows, split[rows]] > threshold[at[rows]])
        value *= rate
        margin += value[at]
        grown.append((feature, threshold, value))
    return Trees(*(np.stack(z) for z in zip(*grown, strict=True)), start, depth)


# ------------------------------------------------------------------- operators


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str = "quality", rows: int = SAMPLE_ROWS, id_col: str = "doc_id", text_col: str = "text") -> tuple[np.ndarray, np.ndarray]:
    """Features and labels of at most ``rows`` labelled documents (two small arrays on the driver)."""
    known = labels.select(F.col(id_col).cast("long").alias("doc_id"), F.col(label).cast("int").alias("y")).where("doc_id is not null and y in (0, 1)")
    known = known.orderBy(F.xxhash64("doc_id"), "doc_id", "y").limit(rows)  # bounded by the parameter, so it may be broadcast
    picked = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("binary").alias("text")).join(F.broadcast(known), "doc_id")

    def run(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([statistics(t)[1] for t in batch.column(1).to_pylist()], pa.list_(pa.float64())), batch.column(2)], names=["doc_id", "x", "y"])

    got = picked.select("doc_id", "text", "y").mapInArrow(run, "doc_id long, x array<double>, y int")
    got = got.orderBy(F.xxhash64("doc_id"), "doc_id", "y", "x").limit(rows).toPandas()  # an id may repeat without bound
    if not len(got):
        return np.zeros((0, len(FEATURES))), np.zeros(0)
    x = np.array(got["x"].tolist())
    order = np.lexsort((*x.T, got["doc_id"].to_numpy()))[:rows]
    return x[order], got["y"].to_numpy(float)[order]


def train(docs: DataFrame, labels: DataFrame, label: str = "quality", rows: int = SAMPLE_ROWS, **how) -> Trees:
    return fit(*labelled_sample(docs, labels, label, rows), tuple(s for _, s in FEATURES), **how)


def score(docs: DataFrame, model: Trees, keep_from: float = 0.5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, score, kept)``, one row per input row.

    A null text counts as empty: no words, so it fails the base rules. Ids are
    passed on, null or repeated as they are; other columns are ignored.
    """
    names = ["doc_id", *BASE, "base_failed", "score", "kept"]

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            base, failed, good = judged(batch.column(1).to_pylist(), model)
            yield pa.RecordBatch.from_arrays([batch.column(0), *map(pa.array, base.T), pa.array(failed), pa.array(good), pa.array(~failed & (good >= keep_from))], names=names)

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("binary").alias("text"))
    return rows.mapInArrow(run, "doc_id long, " + ", ".join(f"{b} long" for b in BASE) + ", base_failed boolean, score double, kept boolean")


def judged(texts: list, model: Trees) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    found = [statistics(t) for t in texts]
    base = np.array([b for b, _ in found], np.int64)
    return base, base_failed(base), model.score(np.array([x for _, x in found]))


def keep_good(docs: DataFrame, model: Trees, keep_from: float = 0.5, text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that the rules keep, all their columns untouched."""
    at = docs.columns.index(text_col)

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                _, failed, good = judged(batch.column(at).cast(pa.binary()).to_pylist(), model)
                yield batch.filter(pa.array(~failed & (good >= keep_from)))

    return docs.mapInArrow(run, docs.schema)
