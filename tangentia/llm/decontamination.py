"""Benchmark decontamination by latent semantic retrieval.

Passages are windows of two blocks of words; items longer than that are cut into passages of about that length too. Their
TF-IDF vectors over the benchmark's terms (very common ones pruned, as TF-IDF does) are never held together: a randomised SVD
takes one pass. With A the blocks' rows and W a random matrix, each task sums its part of A' A W, and from W and that
sum alone the leading right singular vectors and values follow (a Nystroem form). In that whitened space, a text's window
that is near one of an item's passages is a candidate for the item. So is, as an exact way for what the reduced space
misses, a window whose surroundings hold enough of the passage's terms.

Candidates are decided on the whole item by the longest common subsequence of words: an item is leaked if most of its words
stand there in order, or (a paraphrase) if fewer do but its answer, the last quarter, is there nearly whole.

Items come in blocks of bounded size; a block's terms and vectors are what the driver and each task hold.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tangentia.llm import textkit
from tangentia.session import ship_package

BLOCK_WORDS = 20
RANK, MORE = 128, 16
MOST_COMMON = 0.02  # share of blocks beyond which a term is pruned
COSINE = 0.35  # of a window and an item's passage, from which the two are candidates
SCREEN = 0.5  # share of a passage's terms, likewise
WHOLE, PART, ANSWER = 0.8, 0.6, 0.8
ITEMS_PER_BLOCK = 2_000
WIDE_ITEM = 1 << 14  # words from which an item's subsequence is found by places, not by masks of bits: the same result, in less memory
TILE = 512
CHUNK = 16
SEED = 11
NEVER = 1 << 30  # more terms than surroundings can hold


@dataclass
class Items:
    """One block of items: words and terms of each, and the model over them."""

    ids: list
    words: list[np.ndarray]
    terms: np.ndarray  # sorted hashes
    cuts: list[tuple[int, int, int]] = field(default_factory=list)  # passages: item, first word, end
    idf: np.ndarray | None = None  # 0: pruned
    project: np.ndarray | None = None  # (terms, rank): idf times whitened singular vectors
    vectors: np.ndarray | None = None  # (passages, rank), of length 1

    def columns(self, h: np.ndarray) -> np.ndarray:
        """The term of each hash, or -1: a look into a sparse table by leading bits, and a search where terms share a place."""
        if not len(self.terms) or not len(h):
            return np.full(len(h), -1, np.int64)
        if not hasattr(self, "_table"):
            bits = int(np.ceil(np.log2(len(self.terms) + 1))) + 6
            self._shift = np.uint64(64 - bits)
            place = (self.terms >> self._shift).astype(np.int64)
            self._table = np.full(1 << bits, -1, np.int32)
            self._table[place] = np.arange(len(place))
            again = place[1:][place[1:] == place[:-1]]
            self._table[again] = -2
        at = self._table[(h >> self._shift).view(np.int64)].astype(np.int64)
        many = np.flatnonzero(at == -2)
        if len(many):
            at[many] = np.minimum(np.searchsorted(self.terms, h[many]), len(self.terms) - 1)
        at[(at >= 0) & (self.terms[at] != h)] = -1
        return at

    def prepare(self) -> None:
        """What only depends on the model: where an item has each word, the passages of each term, and what the screen asks for."""
        self.length = np.array([len(w) for w in self.words])
        self.places = [_places(w) for w in self.words]
        self.owner = np.array([q for q, *_ in self.cuts])
        pairs, kept, reach = [], [], []
        for k, (q, a, b) in enumerate(self.cuts):
            own = np.unique(self.columns(self.words[q][a:b]))
            own = own[own >= 0]
            own = own[self.idf[own] > 0]
            kept.append(len(own))
            reach.append(min(1.0, 2 * BLOCK_WORDS / max(b - a, 1)))
            pairs += [(c, k) for c in own]
        kept = np.array(kept)
        self.need = np.maximum(1, np.ceil(SCREEN * kept * np.array(reach))).astype(np.int32)
        # a leaked item leaves out at most so many of its words, so this many of its terms must stand in the region; passages of longer items say nothing of that
        missing = np.floor((1 - PART) * self.length[self.owner] + 1e-9).astype(int)
        whole = np.bincount(self.owner, minlength=len(self.words))[self.owner] == 1
        self.least = np.where(whole, kept - missing, 0)
        self.reach = -(-self.length[self.owner] // BLOCK_WORDS)  # blocks of a region to each side of its window
        # a passage of common words only calls for nothing; an item of nothing else is compared with every window
        alone = np.bincount(self.owner, weights=kept, minlength=len(self.words)) == 0
        first = np.r_[True, self.owner[1:] != self.owner[:-1]]
        self.need[kept == 0] = NEVER
        self.need[alone[self.owner] & first] = 0
        self.vectors[kept == 0] = 0
        table = np.array(sorted(pairs), np.int64).reshape(-1, 2)
        self.of_term = table[:, 1]
        self.term_first = np.searchsorted(table[:, 0], np.arange(len(self.terms) + 1))


def _places(words: np.ndarray) -> dict:
    """Of each word, a mask of its places; of a very long item, the list of its places, last one first."""
    found: dict = {}
    if len(words) <= WIDE_ITEM:
        for k, x in enumerate(words.tolist()):
            found[x] = found.get(x, 0) | (1 << k)
    else:
        for k in range(len(words) - 1, -1, -1):
            found.setdefault(int(words[k]), []).append(k)
    return found


def passages_of(length: int) -> list[tuple[int, int]]:
    """(first word, end) of even passages of about two blocks; a text of less than three blocks is one."""
    n = max(1, round(length / (2 * BLOCK_WORDS)))
    at = [length * k // n for k in range(n + 1)]
    return list(zip(at[:-1], at[1:], strict=True))


def words_of(buf: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(text, hash) of each run of letters and digits, without regard to the case of Latin letters."""
    text, start, end = textkit.word_spans(buf, offs, textkit.ALNUM)
    return text, textkit.span_hashes(textkit.fold_case(buf), start, end, lower=False)


def blocks_of(text: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(block of each word, first block of each text, first word of each text)."""
    count = textkit.text_counts(text, n)
    first = np.concatenate([[0], np.cumsum(count)])
    per_text = (count + BLOCK_WORDS - 1) // BLOCK_WORDS
    block = np.concatenate([[0], np.cumsum(per_text)])
    return block[text] + (np.arange(len(text)) - first[text]) // BLOCK_WORDS, block, first


def load_items(rows: list[tuple]) -> Items:
    ids, words, cuts = [], [], []
    for item_id, text in rows:
        data = np.frombuffer((text or "").encode(), np.uint8)
        _, h = words_of(data, np.array([0, len(data)]))
        if len(h):
            cuts += [(len(ids), a, b) for a, b in passages_of(len(h))]
            ids.append(item_id)
            words.append(h)
    return Items(ids, words, np.unique(np.concatenate(words)) if words else np.zeros(0, np.uint64), cuts)


def _runs_of(batches: Iterator[pa.RecordBatch], column: int = 0):
    for batch in batches:
        buf, offs = textkit.text_buffer(batch.column(column))
        for _, _, b, o in textkit.runs(buf, offs):
            text, h = words_of(b, o)
            if len(h):
                yield (len(o) - 1, text, h)


def _sum_runs(values: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(keys, sums of rows) over runs of equal keys."""
    first = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
    return keys[first], np.add.reduceat(values, first)


def _random_matrix(m: int) -> np.ndarray:
    return np.random.default_rng(SEED).standard_normal((m, RANK + MORE), dtype=np.float32)


def block_frequencies(docs: DataFrame, items: Items) -> tuple[np.ndarray, int]:
    """How many blocks of all documents hold each term, and how many blocks there are."""
    shared = docs.sparkSession.sparkContext.broadcast(items)

    def count(batches):
        own, m = shared.value, len(shared.value.terms)
        total, blocks = np.zeros(m, np.int64), 0
        for n, text, h in _runs_of(batches):
            block, bounds, _ = blocks_of(text, n)
            blocks += int(bounds[-1])
            c = own.columns(h)
            hit = c >= 0
            total += np.bincount(np.unique(block[hit] * m + c[hit]) % m, minlength=m)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(np.r_[-1, at]), pa.array(np.r_[blocks, total[at]])], ["term", "n"])
        textkit.tidy()

    out = np.zeros(len(items.terms), np.int64)
    n_blocks = 0
    counted = docs.select("text").mapInArrow(count, "term long, n long").groupBy("term").agg(F.sum("n")).collect()
    shared.destroy()
    for term, n in counted:
        if term < 0:
            n_blocks = n
        else:
            out[term] = n
    return out, n_blocks


def sketch_gram(docs: DataFrame, items: Items) -> np.ndarray:
    """A' A W, summed over all blocks of all documents, in chunks of terms."""
    shared = docs.sparkSession.sparkContext.broadcast(items)
    wide = RANK + MORE

    def part(batches):
        own, m = shared.value, len(shared.value.terms)
        weighted = _random_matrix(m) * own.idf[:, None].astype(np.float32)
        total = np.zeros((m, wide), np.float64)
        for n, text, h in _runs_of(batches):
            block, bounds, _ = blocks_of(text, n)
            c = own.columns(h)
            hit = np.flatnonzero((c >= 0) & (own.idf[np.maximum(c, 0)] > 0))
            if not len(hit):
                continue
            c, block = c[hit], block[hit]
            rows, sums = _sum_runs(weighted[c], block)
            y = np.zeros((bounds[-1], wide), np.float32)
            y[rows] = sums
            order = np.argsort(c, kind="stable")
            terms, sums = _sum_runs(y[block[order]], c[order])
            total[terms] += sums * own.idf[terms][:, None]
        chunks = range(0, m, CHUNK)
        yield pa.RecordBatch.from_arrays([pa.array([k // CHUNK for k in chunks], pa.int32()), pa.array([total[k : k + CHUNK].astype(np.float32).tobytes() for k in chunks], pa.binary())], ["chunk", "z"])
        del weighted, total
        textkit.tidy()

    def add(batches):
        total: dict[int, np.ndarray] = {}
        for batch in batches:
            for k, z in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                z = np.frombuffer(z.as_buffer(), np.float32).astype(np.float64)
                total[k] = total[k] + z if k in total else z
        yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int32()), pa.array([z.astype(np.float32).tobytes() for z in total.values()], pa.binary())], ["chunk", "z"])

    parts = docs.select("text").mapInArrow(part, "chunk int, z binary")
    summed = parts.repartition("chunk").mapInArrow(add, "chunk int, z binary").collect()
    shared.destroy()
    z = np.zeros((len(items.terms), wide))
    for k, data in summed:
        rows = np.frombuffer(data, np.float32).reshape(-1, wide)
        z[k * CHUNK : k * CHUNK + len(rows)] = rows
    return z


def fit_items(docs: DataFrame, items: Items) -> Items:
    """Adds idf, projection and item vectors: two passes over ``docs``, whose results are as large as the block's terms."""
    df, n_blocks = block_frequencies(docs, items)
    items.idf = np.where(df <= max(1.0, MOST_COMMON * n_blocks), np.log((n_blocks + 1) / (df + 1)) + 1e-6, 0.0)
    z = sketch_gram(docs, items)
    core = _random_matrix(len(items.terms)).astype(np.float64).T @ z
    value, vector = np.linalg.eigh((core + core.T) / 2)
    good = value > max(value.max(initial=0), 1e-300) * 1e-9
    if good.any():
        left, size, _ = np.linalg.svd(z @ (vector[:, good] / np.sqrt(value[good])), full_matrices=False)
        keep = size > size[0] * 1e-6
        left, size = left[:, keep][:, :RANK], size[keep][:RANK]
    else:
        left, size = np.zeros((len(items.terms), 1)), np.ones(1)
    items.project = (left / size * items.idf[:, None]).astype(np.float32)
    vectors = np.stack([items.project[items.columns(items.words[q][a:b])].sum(0) for q, a, b in items.cuts])
    items.vectors = (vectors / (np.linalg.norm(vectors, axis=1, keepdims=True) + 1e-12)).astype(np.float32)
    textkit.tidy()
    return items


def common_subsequence(masks: dict[int, int], length: int, words: list[int]) -> int:
    """Bits of the item's words that are matched, in order, by ``words`` (bit-parallel longest common subsequence)."""
    full = (1 << length) - 1
    v = full
    for w in words:
        m = masks.get(w)
        if m:
            u = v & m
            v = ((v + u) | (v - u)) & full
    return full & ~v


def common_places(places: dict[int, list[int]], words: list[int]) -> list[int]:
    """The places of those bits, from lists of places: for each length, the least place at which a common subsequence of it ends."""
    ends: list[int] = []
    for w in words:
        for k in places.get(w, ()):
            at = bisect_left(ends, k)
            ends[at : at + 1] = [k]
    return ends


def shares(items: Items, q: int, words: list[int]) -> tuple[float, float]:
    """(share of the item's words, and of its last quarter's) that ``words`` holds in order."""
    size = int(items.length[q])
    tail = max(1, size // 4)
    if size <= WIDE_ITEM:
        bits = common_subsequence(items.places[q], size, words)
        return bits.bit_count() / size, (bits >> (size - tail)).bit_count() / tail
    ends = common_places(items.places[q], words)
    return len(ends) / size, (len(ends) - bisect_left(ends, size - tail)) / tail


def regions(blocks: list[int], size: int) -> Iterator[tuple[int, int, int]]:
    """(first word, end, a candidate block) of the stretches around candidate blocks, in words from the text's first, in which the item may lie.

    A short item has one for each block. Those of a long item, which reach an item's length to both sides, are joined where
    they begin within half of that.
    """
    step = size // 2 if size > 4 * BLOCK_WORDS else 0
    at = 0
    while at < len(blocks):
        last = at
        while last + 1 < len(blocks) and (blocks[last + 1] - blocks[at]) * BLOCK_WORDS <= step:
            last += 1
        yield blocks[at] * BLOCK_WORDS - size, (blocks[last] + 2) * BLOCK_WORDS + size, blocks[at]
        at = last + 1


def find_leaks(items: Items, n: int, text: np.ndarray, h: np.ndarray) -> list[tuple[int, int, float, float]]:
    """(text, item, cosine, share of the item's words) of the leaks in one run of texts."""
    if not hasattr(items, "places"):
        items.prepare()
    block, bounds, first = blocks_of(text, n)
    blocks = int(bounds[-1])
    c = items.columns(h)
    hit = np.flatnonzero((c >= 0) & (items.idf[np.maximum(c, 0)] > 0))
    owner = np.searchsorted(bounds, np.arange(blocks), side="right") - 1
    y = np.zeros((blocks, items.project.shape[1]), np.float32)
    terms = np.zeros((0, 2), np.int64)
    if len(hit):
        rows, sums = _sum_runs(items.project[c[hit]], block[hit])
        y[rows] = sums
        pair = np.unique(block[hit] * len(items.terms) + c[hit])
        terms = np.stack([pair // len(items.terms), pair % len(items.terms)], 1)
    joined = np.zeros(blocks, bool)  # a block and the next one are of the same text
    joined[:-1] = owner[1:] == owner[:-1]
    window = y.copy()
    window[:-1][joined[:-1]] += y[1:][joined[:-1]]
    window /= np.linalg.norm(window, axis=1, keepdims=True) + 1e-12
    fan = items.term_first[terms[:, 1] + 1] - items.term_first[terms[:, 1]]  # items of each term
    expand = np.repeat(np.arange(len(terms)), fan)
    offset = np.arange(len(expand)) - np.repeat(np.cumsum(fan) - fan, fan)
    of_item = items.of_term[items.term_first[terms[expand, 1]] + offset] if len(expand) else np.zeros(0, np.int64)
    of_block = terms[expand, 0]
    n_words = (first[1:] - first[:-1])[owner]
    near: dict[tuple[int, int], dict[int, float]] = {}  # (text, item): cosine of each candidate block
    for low in range(0, len(items.cuts), TILE):
        high = min(low + TILE, len(items.cuts))
        here = (of_item >= low) & (of_item < high)
        count = np.bincount(of_block[here] * (high - low) + of_item[here] - low, minlength=blocks * (high - low)).reshape(blocks, -1).astype(np.int16)
        around = count.copy()
        around[:-1][joined[:-1]] += count[1:][joined[:-1]]  # the window's two blocks
        around[1:][joined[:-1]] += count[:-1][joined[:-1]]  # the one before
        if blocks > 2:
            both = joined[:-2] & joined[1:-1]
            around[:-2][both] += count[2:][both]  # the one after
        cosine = window @ items.vectors[low:high].T
        # a window is a small part of what stands around a short item, so enough of its terms will do whatever the cosine
        candidate = (around >= items.need[low:high]) | (cosine >= COSINE)
        candidate &= n_words[:, None] >= PART * items.length[items.owner[low:high]]
        at_block, at_item = np.nonzero(candidate)
        running = np.concatenate([np.zeros((1, high - low), np.int32), np.cumsum(count, axis=0, dtype=np.int32)])
        side = items.reach[low + at_item]
        before, after = np.maximum(at_block - side, bounds[owner[at_block]]), np.minimum(at_block + 2 + side, bounds[owner[at_block] + 1])
        enough = running[after, at_item] - running[before, at_item] >= items.least[low + at_item]
        for b, k in zip(at_block[enough], at_item[enough], strict=True):
            own = near.setdefault((int(owner[b]), int(items.owner[low + k])), {})
            at = int(b - bounds[owner[b]])
            own[at] = max(own.get(at, -1.0), float(cosine[b, k]))
    found = []
    for (d, item), blocks_near in near.items():
        size, best = int(items.length[item]), (0.0, 0.0)
        for a, z, at in regions(sorted(blocks_near), size):
            region = h[first[d] + max(0, a) : min(first[d + 1], first[d] + z)]
            if size > 4 * BLOCK_WORDS and np.isin(region, items.words[item]).sum() < PART * size:
                continue  # so few of its words, in any order
            share, answer = shares(items, item, region.tolist())
            if share >= WHOLE or (share >= PART and answer >= ANSWER):
                best = max(best, (share, blocks_near[at]))
                if share == 1:
                    break
        if best[0]:
            found.append((d, item, best[1], best[0]))
    return found


def item_blocks(benchmark: DataFrame, size: int = ITEMS_PER_BLOCK) -> Iterator[Items]:
    """The items, in blocks of about ``size`` by hash of their ids; null and empty items leak nowhere."""
    rows = benchmark.select("item_id", F.col("text").cast("string").alias("text")).where(F.coalesce(F.trim("text"), F.lit("")) != "")
    n = rows.count()
    parts = -(-n // size) if n else 0
    for k in range(parts):
        own = sorted(map(tuple, rows.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(parts)) == k).collect()), key=lambda r: (r[0] is None, r[0] or 0, r[1]))
        items = load_items(own)
        if items.words:
            yield items


def leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """(doc_id, contaminated, item_ids, similarity, cosine) for each row of ``docs``.

    item_ids: the items found in the text, ascending; similarity: the largest share of an item's words found in
    order, 0 where none is leaked; cosine: of that passage. Null and empty texts hold no leak; repeated rows are judged each;
    other columns are ignored; without items nothing is contaminated.
    """
    spark = docs.sparkSession
    ship_package(spark)
    id_type = docs.schema["doc_id"].dataType.simpleString()
    models = [spark.sparkContext.broadcast(fit_items(docs, items)) for items in item_blocks(benchmark)]
    item_type = benchmark.schema["item_id"].dataType.simpleString()

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            items_of: list[list] = [[] for _ in range(batch.num_rows)]
            best = [(0.0, None)] * batch.num_rows
            buf, offs = textkit.text_buffer(batch.column(1))
            for i, j, b, o in textkit.runs(buf, offs):
                text, h = words_of(b, o)
                for model in models if len(h) else ():
                    for d, item, cos, share in find_leaks(model.value, j - i, text, h):
                        items_of[i + d].append(model.value.ids[item])
                        best[i + d] = max(best[i + d], (share, cos), key=lambda x: x[0])
            lists = [sorted(set(x), key=lambda v: (v is None, v)) for x in items_of]
            columns = [batch.column(0), pa.array([bool(x) for x in lists]), pa.array(lists, pa.list_(pa.int64() if item_type == "bigint" else pa.string())), pa.array([s for s, _ in best], pa.float64()), pa.array([x for _, x in best], pa.float64())]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "contaminated", "item_ids", "similarity", "cosine"])

    return docs.select("doc_id", F.col("text").cast("string")).mapInArrow(judge, f"doc_id {id_type}, contaminated boolean, item_ids array<{'bigint' if item_type == 'bigint' else 'string'}>, similarity double, cosine double")


def drop_leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """``docs`` without the rows that hold a benchmark item."""
    spark = docs.sparkSession
    ship_package(spark)
    models = [spark.sparkContext.broadcast(fit_items(docs, items)) for items in item_blocks(benchmark)]
    at = docs.columns.index("text")

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            clean = np.ones(batch.num_rows, bool)
            buf, offs = textkit.text_buffer(batch.column(at))
            for i, j, b, o in textkit.runs(buf, offs):
                text, h = words_of(b, o)
                for model in models if len(h) else ():
                    for d, *_ in find_leaks(model.value, j - i, text, h):
                        clean[i + d] = False
            yield batch.filter(pa.array(clean))
        textkit.tidy()

    return docs.mapInArrow(keep, docs.schema)
