"""Quality scores from histogram gradient-boosted trees over document statistics.

Statistics come from passes of numpy over a batch's bytes: shares of byte classes, word and line lengths, how often
words, word pairs and lines repeat. Trees are grown level by level on quantile bins (one histogram of gradients for each
node, statistic and bin) and stored as flat arrays, complete to their depth; all rows of a batch go down all
trees together, an array step for each level.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tangentia.llm import textkit
from tangentia.llm.labelled import labelled_texts, remainder, sample_labels
from tangentia.session import ship_package

SAMPLE_ROWS = 20_000  # labelled rows that a model is fitted on, at most twice that
SAMPLE_BYTES = 1 << 16  # longer texts are scored, but no model is fitted on them
CLASSES = ("control", "space", "newline", "upper", "lower", "digit", "stop", "comma", "exclaim", "bar", "symbol", "bracket", "other", "high")
NAMES = tuple(f"share_{c}" for c in CLASSES) + (
    "log_bytes", "log_words", "word_bytes", "word_bytes_sd", "long_words", "short_words", "upper_words", "symbol_ends",
    "distinct_words", "top_word", "same_as_last", "same_as_before_last", "distinct_pairs", "line_words", "repeated_lines", "byte_entropy",
)

_CLASS = np.full(256, CLASSES.index("other"), np.uint8)
for _name, _bytes in (
    ("control", bytes(range(32))), ("space", b" \t"), ("newline", b"\n\r"), ("upper", bytes(range(65, 91))), ("lower", bytes(range(97, 123))),
    ("digit", b"0123456789"), ("stop", b".?"), ("comma", b",;:'\"-"), ("exclaim", b"!"), ("bar", b"|"), ("symbol", b"#$%&*@^~+=_\\"), ("bracket", b"()[]{}<>"), ("high", bytes(range(128, 256))),
):
    _CLASS[list(_bytes)] = CLASSES.index(_name)


def _distinct(text: np.ndarray, h: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """For each text, how many different hashes it has and how often the most frequent one occurs."""
    if not len(h):
        return np.zeros(n), np.zeros(n)
    order = np.lexsort((h, text))
    t, s = text[order], h[order]
    new = np.ones(len(s), bool)
    new[1:] = (s[1:] != s[:-1]) | (t[1:] != t[:-1])
    at = np.flatnonzero(new)
    length = np.diff(np.append(at, len(s)))
    top = np.zeros(n)
    np.maximum.at(top, t[at], length)
    return np.bincount(t[at], minlength=n).astype(float), top


def statistics(buf: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """(texts, NAMES) of one run of texts; an empty text has zeros."""
    n = len(offs) - 1
    size = np.diff(offs).astype(float)
    per_byte = 1 / np.maximum(size, 1)
    owner = np.repeat(np.arange(n), np.diff(offs))
    shares = np.bincount(owner * len(CLASSES) + _CLASS[buf], minlength=n * len(CLASSES)).reshape(n, -1) * per_byte[:, None]
    entropy = np.zeros(n)
    for i in range(n):
        p = np.bincount(buf[offs[i] : offs[i + 1]], minlength=1)
        p = p[p > 0] * per_byte[i]
        entropy[i] = -(p * np.log2(p)).sum() if len(p) else 0
    text, starts, ends = textkit.word_spans(buf, offs, textkit.SPACED)
    h = textkit.span_hashes(buf, starts, ends)
    words = np.bincount(text, minlength=n).astype(float)
    per_word = 1 / np.maximum(words, 1)
    total = lambda x: np.bincount(text, weights=x, minlength=n)
    length = (ends - starts).astype(float)
    mean = total(length) * per_word
    kind = _CLASS[buf]
    upper_before = np.concatenate([[0], np.cumsum(kind == CLASSES.index("upper"))])
    upper = upper_before[ends] - upper_before[starts]
    last = kind[ends - 1] if len(ends) else np.zeros(0, np.uint8)
    distinct, top = _distinct(text, h, n)
    same = np.zeros((2, len(h)))
    for k in (1, 2):
        same[k - 1, k:] = (h[k:] == h[:-k]) & (text[k:] == text[:-k])
    pair = textkit.mix(h[:-1] * textkit.BASE + h[1:]) if len(h) > 1 else np.zeros(0, np.uint64)
    within = text[1:] == text[:-1]
    pairs, _ = _distinct(text[1:][within], pair[within], n)
    newline = np.ones(256, bool)
    newline[[10, 13]] = False
    line_text, line_starts, line_ends = textkit.word_spans(buf, offs, newline)
    lines = np.bincount(line_text, minlength=n).astype(float)
    distinct_lines, _ = _distinct(line_text, textkit.span_hashes(buf, line_starts, line_ends), n)
    columns = [
        np.log1p(size), np.log1p(words), mean, np.sqrt(np.maximum(total(length**2) * per_word - mean**2, 0)), total(length > 20) * per_word, total(length <= 3) * per_word,
        total((upper > 1) & (2 * upper > length)) * per_word, total((last == CLASSES.index("symbol")) | (last == CLASSES.index("exclaim"))) * per_word,
        distinct * per_word, top * per_word, total(same[0]) * per_word, total(same[1]) * per_word, pairs / np.maximum(words - 1, 1), words / np.maximum(lines, 1),
        1 - distinct_lines / np.maximum(lines, 1), entropy,
    ]
    out = np.hstack([shares, np.stack(columns, 1)])
    out[size == 0] = 0
    return out.astype(np.float32)


def batch_statistics(column: pa.Array) -> np.ndarray:
    buf, offs = textkit.text_buffer(column)
    parts = [statistics(b, o) for *_, b, o in textkit.runs(buf, offs)]
    return np.concatenate(parts) if parts else np.zeros((0, len(NAMES)), np.float32)


@dataclass
class BoostedTrees:
    """Trees complete to one depth: node k of a tree has the children 2k + 1 and 2k + 2, and leaves follow the inner nodes."""

    feature: np.ndarray  # (trees, inner nodes)
    threshold: np.ndarray  # (trees, inner nodes): rows above it go right
    leaf: np.ndarray  # (trees, leaves)
    start: float

    def margin(self, x: np.ndarray) -> np.ndarray:
        total, rows = np.full(len(x), self.start), np.arange(len(x))
        inner = self.feature.shape[1]
        for f, t, v in zip(self.feature, self.threshold, self.leaf, strict=True):
            node = np.zeros(len(x), np.int64)
            while inner and node[0] < inner:
                node = 2 * node + 1 + (x[rows, f[node]] > t[node])
            total += v[node - inner]
        return total

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-self.margin(x))) if len(x) else np.zeros(0)


def fit_trees(x: np.ndarray, y: np.ndarray, weight: np.ndarray, trees: int = 80, depth: int = 4, rate: float = 0.15, bins: int = 64, ridge: float = 1.0, least: float = 5.0) -> BoostedTrees:
    """Logistic loss, second order. Without rows of both labels the score is constant: that label's, or 0.5."""
    inner, leaves = 2**depth - 1, 2**depth
    if not len(y) or y.min() == y.max():
        start = 0.0 if not len(y) else (4.0 if y[0] else -4.0)
        return BoostedTrees(np.zeros((0, inner), np.int64), np.zeros((0, inner), np.float32), np.zeros((0, leaves)), start)
    n, m = x.shape
    cuts = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1], method="lower")) for j in range(m)]
    binned = np.stack([np.searchsorted(c, x[:, j], side="left") for j, c in enumerate(cuts)], 1)
    flat = binned + np.arange(m) * bins
    mean = np.average(y, weights=weight)
    start = float(np.log(mean / (1 - mean)))
    margin = np.full(n, start)
    features, thresholds, values = [], [], []
    for _ in range(trees):
        p = 1 / (1 + np.exp(-margin))
        g, h = weight * (p - y), weight * p * (1 - p)
        feature, threshold = np.zeros(inner, np.int64), np.full(inner, np.inf, np.float32)
        node = np.zeros(n, np.int64)
        for level in range(depth):
            first, wide = 2**level - 1, 2**level
            key = ((node - first)[:, None] * (m * bins) + flat).ravel()
            sums = [np.bincount(key, weights=np.repeat(w, m), minlength=wide * m * bins).reshape(wide, m, bins).cumsum(2) for w in (g, h)]
            (gl, hl), (gt, ht) = sums, (sums[0][:, :, -1:], sums[1][:, :, -1:])
            gain = gl**2 / (hl + ridge) + (gt - gl) ** 2 / (ht - hl + ridge) - gt**2 / (ht + ridge)
            gain[(hl < least / 4) | (ht - hl < least / 4)] = 0
            best = gain.reshape(wide, -1).argmax(1)
            for k in range(wide):
                j, b = divmod(int(best[k]), bins)
                if gain[k, j, b] > 1e-6 and b < len(cuts[j]):
                    feature[first + k], threshold[first + k] = j, cuts[j][b]
            node = 2 * node + 1 + (x[np.arange(n), feature[node]] > threshold[node])
        leaf = node - inner
        value = -rate * np.bincount(leaf, weights=g, minlength=leaves) / (np.bincount(leaf, weights=h, minlength=leaves) + ridge)
        margin += value[leaf]
        features.append(feature)
        thresholds.append(threshold)
        values.append(value)
    return BoostedTrees(np.stack(features), np.stack(thresholds), np.stack(values), start)


def _statistics_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        s = batch_statistics(batch.column(2))
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(list(s), pa.list_(pa.float32()))], ["y", "weight", "s"])


def fit_quality(docs: DataFrame, labels: DataFrame, label: str = "quality", at_most: int = SAMPLE_ROWS) -> BoostedTrees:
    """A model from a bounded sample of labelled rows; statistics are made where the texts are, and only they reach the driver."""
    ship_package(docs.sparkSession)
    texts = labelled_texts(docs, sample_labels(labels, label, at_most), SAMPLE_BYTES)
    rows = texts.mapInArrow(_statistics_batches, "y int, weight double, s array<float>").toArrow()
    x = np.asarray(rows["s"].combine_chunks().flatten()).reshape(-1, len(NAMES)) if len(rows) else np.zeros((0, len(NAMES)), np.float32)
    y, w = np.asarray(rows["y"], float), np.asarray(rows["weight"], float)
    order = np.lexsort(np.column_stack([x, y]).T) if len(rows) else slice(None)  # the same model, whatever order rows arrive in
    return fit_trees(x[order], y[order], w[order])


def score_quality(docs: DataFrame, model: BoostedTrees) -> DataFrame:
    """(doc_id, score, predicted) for each row; null and empty texts have the score of all-zero statistics; repeated rows are scored each."""
    ship_package(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    id_type = docs.schema["doc_id"].dataType.simpleString()

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            s = shared.value.score(batch_statistics(batch.column(1)))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(s, pa.float64()), pa.array((s >= 0.5).astype(np.int32))], ["doc_id", "score", "predicted"])

    return docs.select("doc_id", F.col("text").cast("string")).mapInArrow(score, f"doc_id {id_type}, score double, predicted int")


def quality_scores(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(doc_id, held_out, score, predicted): fitted on ids whose remainder by 3 is not 1, where held_out is false (null ids too)."""
    learn = labels.where(remainder(F.col("doc_id"), 3) != 1)
    scored = score_quality(docs, fit_quality(docs, learn))
    return scored.select("doc_id", F.coalesce(remainder(F.col("doc_id"), 3) == 1, F.lit(False)).alias("held_out"), "score", "predicted")
