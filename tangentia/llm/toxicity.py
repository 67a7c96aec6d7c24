"""Toxic spans from a linear-chain conditional random field; its marginals give document scores and offsets.

Only documents are labelled, so tokens are labelled from them: a word, or a word's beginning, that stands in far more different contexts in toxic
documents than their number would give by chance (a likelihood ratio against the number of words tried) is
toxic where it occurs in a toxic document. A document stands for the least of its contexts of the word by hash,
which copies share, so a copied document is one piece of evidence. The field has the states clean and toxic over the words of a sentence; a word's own
hash, those of its beginnings, its neighbours', its first and last letters and its length weigh on its state.

All sentences of a batch run forward and backward together: for two states each message is one number (the odds),
and one array step moves all sentences by a word. A document's score comes from its largest marginal and
from the sum of its marginals by a logistic curve, fitted on the same bounded sample.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tangentia.llm import textkit
from tangentia.llm.labelled import labelled_texts, remainder, sample_labels
from tangentia.session import ship_package

SAMPLE_ROWS = 2_400  # labelled rows that a model is fitted on, at most twice that
SAMPLE_BYTES = 1 << 14  # longer texts are scored, but no model is fitted on them
LETTERS = 1 << 15
LENGTHS = 16
BEGINNINGS = (4, 5, 6, 7)  # bytes of a word's beginnings that count as words of their own
WINDOW = 24
SEEN = 3  # a word has weights of its own from so many occurrences in the sample
MAX_ODDS = 1e12

_ends = np.zeros(256, bool)
_ends[list(b"\n\r.!?")] = True


@dataclass
class Tokens:
    text: np.ndarray
    start: np.ndarray
    end: np.ndarray
    hash: np.ndarray
    keys: list[np.ndarray]  # the word, then its beginnings; 0 where the word is no longer than that
    head: np.ndarray
    tail: np.ndarray
    length: np.ndarray
    sentence: np.ndarray  # numbered from 0, never across texts


def tokenise(buf: np.ndarray, offs: np.ndarray) -> Tokens:
    """Runs of letters and digits, A-Z lower-cased; a line break or . ! ? between two ends a sentence."""
    text, start, end = textkit.word_spans(buf, offs, textkit.ALNUM)
    low = textkit.LOWER[buf].astype(np.uint64)
    last = end - 1
    three = lambda at, step: low[at] | (np.where((at + step < end) & (at + step >= start), low[np.clip(at + step, 0, max(len(low) - 1, 0))], 0) << np.uint64(8)) | (np.where((at + 2 * step < end) & (at + 2 * step >= start), low[np.clip(at + 2 * step, 0, max(len(low) - 1, 0))], 0) << np.uint64(16))
    letters = lambda x: (textkit.mix(x) % np.uint64(LETTERS)).astype(np.int64)
    stops = np.concatenate([[0], np.cumsum(_ends[buf])])
    new = np.ones(len(start), bool)
    if len(start):
        new[1:] = (text[1:] != text[:-1]) | (stops[start[1:]] > stops[end[:-1]])
    hasher = textkit.SpanHasher(buf)
    keys = [hasher(start, end)]
    for k in BEGINNINGS:
        keys.append(np.where(end - start > k, textkit.mix(hasher(start, np.minimum(start + k, end)) + np.uint64(k)), np.uint64(0)))
    return Tokens(text, start, end, keys[0], keys, letters(three(start, 1)), letters(three(last, -1)), np.minimum((end - start) // 2, LENGTHS - 1), np.cumsum(new) - 1)


@dataclass
class Field:
    """Weights in arrays; words by sorted hash, and row 0 of ``own``, ``before``, ``after`` is any other word's."""

    words: np.ndarray
    own: np.ndarray
    before: np.ndarray
    after: np.ndarray
    head: np.ndarray
    tail: np.ndarray
    length: np.ndarray
    bias: float
    moves: np.ndarray  # (from, to)
    curve: np.ndarray  # constant, largest marginal's log odds, log of the marginals' sum

    def slots(self, h: np.ndarray) -> np.ndarray:
        if not len(self.words):
            return np.zeros(len(h), np.int64)
        if not hasattr(self, "_table"):
            bits = max(4, int(np.ceil(np.log2(len(self.words)))) + 4)
            self._shift = np.uint64(64 - bits)
            at = (self.words >> self._shift).astype(np.int64)
            self._table = np.searchsorted(at, np.arange((1 << bits) + 1))  # first word of each range of hashes
            self._deep = int(np.diff(self._table).max())
        at = (h >> self._shift).astype(np.int64)
        low, high = self._table[at], self._table[at + 1]
        found = np.zeros(len(h), np.int64)
        for k in range(self._deep):
            where = low + k
            live = np.flatnonzero(where < high)
            hit = live[self.words[where[live]] == h[live]]
            found[hit] = where[hit] + 1
        return found

    def emissions(self, t: Tokens) -> np.ndarray:
        slots = [self.slots(k) for k in t.keys]
        slot = slots[0]
        e = self.bias + sum(self.own[k] for k in slots) + self.head[t.head] + self.tail[t.tail] + self.length[t.length]
        same = t.sentence[1:] == t.sentence[:-1]
        e[1:] += np.where(same, self.before[slot[:-1]], 0)
        e[:-1] += np.where(same, self.after[slot[1:]], 0)
        return e


def sentence_blocks(sentence: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(token index, mask), a row for each sentence, of sentences of like length: rows are at most twice as long as their sentence."""
    if not len(sentence):
        return
    size = np.bincount(sentence)
    first = np.concatenate([[0], np.cumsum(size)[:-1]])
    order = np.argsort(size, kind="stable")
    i = 0
    while i < len(order):
        top = max(8, 2 * size[order[i]])
        j = int(np.searchsorted(size[order], top, side="right"))
        j = min(j, i + max(1, (1 << 20) // int(size[order[j - 1]])))
        rows = order[i:j]
        wide = int(size[rows].max())
        mask = np.arange(wide) < size[rows][:, None]
        yield np.where(mask, first[rows][:, None] + np.arange(wide), 0), mask
        i = j


def run_chain(e: np.ndarray, mask: np.ndarray, moves: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(forward odds, backward odds, emission odds) of blocks (sentences, words): odds of toxic against clean."""
    odds = np.where(mask, np.exp(np.clip(e, -25, 25)), 0.0)
    m = np.exp(moves)
    forward, backward = np.empty_like(odds), np.ones_like(odds)
    forward[:, 0] = odds[:, 0]
    for k in range(1, e.shape[1]):
        r = forward[:, k - 1]
        forward[:, k] = np.minimum(odds[:, k] * (m[0, 1] + r * m[1, 1]) / (m[0, 0] + r * m[1, 0]), MAX_ODDS)
    for k in range(e.shape[1] - 2, -1, -1):
        x = odds[:, k + 1] * backward[:, k + 1]
        b = (m[1, 0] + m[1, 1] * x) / (m[0, 0] + m[0, 1] * x)
        backward[:, k] = np.where(mask[:, k + 1], b, 1.0)
    return forward, backward, odds


def marginals(field: Field, t: Tokens) -> np.ndarray:
    """Probability that each word is toxic, given its sentence."""
    e = field.emissions(t)
    out = np.zeros(len(e))
    for at, mask in sentence_blocks(t.sentence):
        f, b, _ = run_chain(e[at], mask, field.moves)
        both = f * b
        out[at[mask]] = (both / (1 + both))[mask]
    return out


def document_features(text: np.ndarray, p: np.ndarray, n: int) -> np.ndarray:
    """(1, log odds of the largest marginal, log of their sum) of each document; one without words has marginals of 0."""
    top, total = np.full(n, 1e-6), np.bincount(text, weights=p, minlength=n)
    np.maximum.at(top, text, np.clip(p, 1e-6, 1 - 1e-6))
    return np.column_stack([np.ones(n), np.log(top / (1 - top)), np.log(total + 1e-3)])


def toxic_keys(t: Tokens, toxic: np.ndarray) -> np.ndarray:
    """Sorted hashes of the words and beginnings whose contexts in toxic documents are too many for chance."""
    if not len(t.hash):
        return np.zeros(0, np.uint64)
    before, after = np.zeros_like(t.hash), np.zeros_like(t.hash)
    same = t.text[1:] == t.text[:-1]
    before[1:] = np.where(same, t.hash[:-1], 0)
    after[:-1] = np.where(same, t.hash[1:], 0)
    around = textkit.mix(before * textkit.BASE + after)
    found = []
    for keys in t.keys:
        own = np.flatnonzero(keys)
        order = own[np.lexsort((around[own], t.text[own], keys[own]))]
        key, text, context = keys[order], t.text[order], around[order]
        least = np.ones(len(key), bool)
        least[1:] = (key[1:] != key[:-1]) | (text[1:] != text[:-1])
        key, context, label = key[least], context[least], toxic[text[least]]
        del order, text
        if not len(key):
            continue
        order = np.lexsort((label, context, key))
        key, context, label = key[order], context[order], label[order]
        new = np.ones(len(key), bool)
        new[1:] = (key[1:] != key[:-1]) | (context[1:] != context[:-1]) | (label[1:] != label[:-1])
        key, label = key[new], label[new]
        each, at = np.unique(key, return_inverse=True)
        k1, k0 = (np.bincount(at, weights=label == y, minlength=len(each)) for y in (True, False))
        share = min(max(k1.sum() / len(key), 1e-9), 1 - 1e-9)
        with np.errstate(divide="ignore", invalid="ignore"):
            gain = k1 * np.log(np.where(k1 > 0, k1 / (k1 + k0), 1) / share) + np.where(k0 > 0, k0 * np.log(k0 / (k1 + k0) / (1 - share)), 0)
        tried = max((k1 + k0 >= 3).sum(), 1)
        found.append(each[(k1 > 3 * k0) & (k1 >= 3) & (k1 / (k1 + k0) > share) & (gain > np.log(tried) + 1)])
    return np.unique(np.concatenate(found))


def fit_field(texts: list[str], y: np.ndarray, weight: np.ndarray, epochs: int = 12, rate: float = 0.3, ridge: float = 1e-5, seed: int = 7) -> Field:
    """Adaptive gradient steps on windows of words around toxic ones and as many drawn elsewhere; then the document curve."""
    random = np.random.default_rng(seed)
    buf, offs = textkit.text_buffer(pa.array(texts, pa.string()))
    t = tokenise(buf, offs)
    telling = toxic_keys(t, y > 0)
    bad = np.zeros(len(t.hash), bool)
    words = []
    for keys in t.keys:  # one kind at a time, which bounds the driver's memory
        if len(telling):
            bad |= telling[np.minimum(np.searchsorted(telling, keys), len(telling) - 1)] == keys
        each, count = np.unique(keys, return_counts=True)
        words.append(each[(count >= SEEN) & (each > 0)])
    bad &= y[t.text] > 0
    words = np.unique(np.concatenate(words))
    w = len(words) + 1
    field = Field(words, np.zeros(w), np.zeros(w), np.zeros(w), np.zeros(LETTERS), np.zeros(LETTERS), np.zeros(LENGTHS), -2.0, np.zeros((2, 2)), np.array([-1.0, 0.0, 0.0]))
    if len(texts):
        prior = np.average(y, weights=weight)
        field.curve[0] = np.log((prior + 1e-3) / (1 - prior + 1e-3))
    if not bad.any():
        return field
    slots = [field.slots(k) for k in t.keys]
    slot = slots[0]
    chunk = np.arange(len(t.hash)) // WINDOW
    window = t.sentence.astype(np.int64) * (chunk.max() + 1) + chunk  # pieces of sentences, of at most WINDOW words
    window = np.unique(window, return_inverse=True)[1]
    with_bad = np.zeros(window.max() + 1, bool)
    with_bad[window[bad]] = True
    others = np.flatnonzero(~with_bad)
    chosen = np.concatenate([np.flatnonzero(with_bad), random.permutation(others)[: max(4 * with_bad.sum(), 2000)]])
    first = np.searchsorted(window, np.arange(window.max() + 2))
    arrays = {"own": field.own, "before": field.before, "after": field.after, "head": field.head, "tail": field.tail, "length": field.length}
    squares = {k: np.full(v.shape, 1e-2) for k, v in arrays.items()} | {"bias": 1e-2, "moves": np.full((2, 2), 1e-2)}
    for _ in range(epochs):
        chosen = random.permutation(chosen)
        for part in np.array_split(chosen, max(1, len(chosen) // 512)):
            size = first[part + 1] - first[part]
            mask = np.arange(size.max()) < size[:, None]
            at = np.where(mask, first[part][:, None] + np.arange(size.max()), 0)
            truth = bad[at] & mask
            s = slot[at]
            has_before, has_after = mask[:, 1:], mask[:, 1:]
            own = np.stack([k[at] for k in slots])
            e = field.bias + field.own[own].sum(0) + field.head[t.head[at]] + field.tail[t.tail[at]] + field.length[t.length[at]]
            e[:, 1:] += np.where(has_before, field.before[s[:, :-1]], 0)
            e[:, :-1] += np.where(has_after, field.after[s[:, 1:]], 0)
            f, b, odds = run_chain(e, mask, field.moves)
            both = f * b
            error = np.where(mask, both / (1 + both) - truth, 0)
            steps = {
                "own": np.bincount(own.ravel(), np.broadcast_to(error, own.shape).ravel(), w),
                "before": np.bincount(s[:, :-1].ravel(), (error[:, 1:] * has_before).ravel(), w),
                "after": np.bincount(s[:, 1:].ravel(), (error[:, :-1] * has_after).ravel(), w),
                "head": np.bincount(t.head[at].ravel(), error.ravel(), LETTERS),
                "tail": np.bincount(t.tail[at].ravel(), error.ravel(), LETTERS),
                "length": np.bincount(t.length[at].ravel(), error.ravel(), LENGTHS),
            }
            x = odds[:, 1:] * b[:, 1:]
            r, m = f[:, :-1], np.exp(field.moves)
            joint = np.stack([np.full_like(x, m[0, 0]), m[0, 1] * x, m[1, 0] * r, m[1, 1] * r * x])
            joint /= joint.sum(0)
            pair = 2 * truth[:, :-1] + truth[:, 1:]
            move = np.array([((joint[k] - (pair == k)) * mask[:, 1:]).sum() for k in range(4)]).reshape(2, 2)
            n = len(part)
            steps["own"][0] = steps["before"][0] = steps["after"][0] = 0  # words not seen have no weight
            for k, g in steps.items():
                g = g / n + ridge * arrays[k]
                squares[k] += g * g
                arrays[k] -= rate * g / np.sqrt(squares[k])
            g = error.sum() / n
            squares["bias"] += g * g
            field.bias -= rate * g / np.sqrt(squares["bias"])
            squares["moves"] += (move / n) ** 2
            field.moves -= rate * (move / n) / np.sqrt(squares["moves"])
    x = document_features(t.text, marginals(field, t), len(texts))
    plain, pull = np.array([0.0, 1.0, 0.0]), np.array([0.5, 2.0, 2.0])  # without much evidence, the largest marginal is the score
    curve = plain.copy()
    for _ in range(30):  # Newton's steps
        p = 1 / (1 + np.exp(-np.clip(x @ curve, -30, 30)))
        h = (x * (weight * p * (1 - p))[:, None]).T @ x + np.diag(pull)
        curve = curve - np.clip(np.linalg.solve(h, x.T @ (weight * (p - y)) + pull * (curve - plain)), -1, 1)
    field.curve = curve
    return field


def _fit_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    data = sorted(((t or "", y, w) for b in batches for t, y, w in zip(*(b.column(c).to_pylist() for c in ("text", "y", "weight")), strict=True)), key=lambda r: r[:2])
    field = fit_field([t for t, _, _ in data], np.array([y for _, y, _ in data], float), np.array([w for *_, w in data], float))
    yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(field)], pa.binary())], ["field"])
    del data, field
    textkit.tidy()


def fit_toxicity(docs: DataFrame, labels: DataFrame, label: str = "toxic", at_most: int = SAMPLE_ROWS) -> Field:
    """A field from a bounded sample of labelled rows: one task gets its texts, at most 2 * ``at_most`` of SAMPLE_BYTES, and the driver only the weights."""
    ship_package(docs.sparkSession)
    texts = labelled_texts(docs, sample_labels(labels, label, at_most), SAMPLE_BYTES)
    rows = texts.repartition(1).mapInArrow(_fit_batches, "field binary").collect()
    return pickle.loads(rows[0]["field"]) if rows else fit_field([], np.zeros(0), np.zeros(0))


def score_batch(field: Field, column: pa.Array, spans: bool, least: float = 0.5) -> tuple[np.ndarray, list]:
    """Scores of texts and, if asked, the (start, end) code points of their words with a marginal of ``least`` or more."""
    scores, found = [], []
    buf, offs = textkit.text_buffer(column)
    for i, j, b, o in textkit.runs(buf, offs):
        t = tokenise(b, o)
        p = marginals(field, t)
        x = document_features(t.text, p, j - i)
        scores.append(1 / (1 + np.exp(-np.clip(x @ field.curve, -30, 30))))
        if spans:
            points = np.concatenate([[0], np.cumsum((b & 0xC0) != 0x80)])
            own: list[list] = [[] for _ in range(j - i)]
            for k in np.flatnonzero(p >= least):
                origin = points[o[t.text[k]]]
                own[t.text[k]].append({"start": int(points[t.start[k]] - origin), "end": int(points[t.end[k]] - origin)})
            found += own
    return np.concatenate(scores) if scores else np.zeros(0), found


def score_toxicity(docs: DataFrame, field: Field, spans: bool = True) -> DataFrame:
    """(doc_id, score, predicted, spans) for each row: spans are (start, end) in code points, end exclusive.

    Null and empty texts have no words and the score of that; repeated rows are scored each; other columns are ignored.
    """
    ship_package(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(field)
    id_type = docs.schema["doc_id"].dataType.simpleString()
    span = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())]))

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            s, found = score_batch(shared.value, batch.column(1), spans)
            columns = [batch.column(0), pa.array(s, pa.float64()), pa.array((s >= 0.5).astype(np.int32))]
            yield pa.RecordBatch.from_arrays([*columns, *([pa.array(found, span)] if spans else [])], ["doc_id", "score", "predicted", "spans"][: 3 + spans])

    more = ", spans array<struct<start:int,end:int>>" if spans else ""
    return docs.select("doc_id", F.col("text").cast("string")).mapInArrow(score, f"doc_id {id_type}, score double, predicted int{more}")


def toxicity_scores(docs: DataFrame, labels: DataFrame, spans: bool = True) -> DataFrame:
    """(doc_id, held_out, score, predicted, spans): fitted on ids whose remainder by 5 is not 0, where held_out is false (null ids too)."""
    learn = labels.where(remainder(F.col("doc_id"), 5) != 0)
    scored = score_toxicity(docs, fit_toxicity(docs, learn), spans)
    held = F.coalesce(remainder(F.col("doc_id"), 5) == 0, F.lit(False)).alias("held_out")
    return scored.select("doc_id", held, *scored.columns[1:])


def drop_toxic(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``docs`` without the rows whose score is 0.5 or more; fitted on the labelled rows among ``docs``. Clean rows are left as they are."""
    ship_package(docs.sparkSession)
    field = fit_toxicity(docs, labels)
    shared = docs.sparkSession.sparkContext.broadcast(field)
    kept = [docs.columns.index("text")]

    def drop(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            s, _ = score_batch(shared.value, batch.column(kept[0]), False)
            yield batch.filter(pa.array(s < 0.5))
        textkit.tidy()

    return docs.mapInArrow(drop, docs.schema)
