"""Token counts of whole texts; huge texts go in overlapping chunks that are spliced where both encodings prove to agree.

A byte-level BPE first parts a text into pieces that it encodes one by one. Between an ASCII letter and a
space that an ASCII letter follows, every such parting cuts, whatever stands around: letters and spaces share no
piece but for a leading space, and no special token holds a space between letters. A chunk is encoded with offsets; it
and the next overlap, and the counts are spliced at the last place in the overlap that is such a place and at
which both encodings start a token, after which they agree. If there is none, the overlap is widened until there
is, at worst to the end of the text.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tangentia.session import ship_package

CHUNK_CHARS = 1 << 18
OVERLAP_CHARS = 1 << 10
BATCH_CHARS = 1 << 21
STABLE = re.compile(r"(?<=[A-Za-z])(?= [A-Za-z])")
_loaded: dict = {}


def load_tokenizer(path: str):
    if path not in _loaded:
        from tokenizers import Tokenizer

        t = Tokenizer.from_file(path)
        t.no_truncation()
        t.no_padding()
        _loaded[path] = t
    return _loaded[path]


def count_chunked(text: str, tokenizer, chunk: int = CHUNK_CHARS, overlap: int = OVERLAP_CHARS) -> int:
    """Tokens of one text: the same number as of one encoding of it, holding one chunk's tokens at a time."""
    encode = lambda a, b: [s + a for s, _ in tokenizer.encode(text[a:b], add_special_tokens=False).offsets]
    total, begin, n = 0, 0, len(text)
    while begin < n:
        end, wide = min(begin + chunk, n), overlap
        starts = encode(begin, end)
        while end < n:
            head, stop = max(begin, end - wide), min(n, end + wide)
            places = [m.start() for m in STABLE.finditer(text, head + 1, end)]
            if places:
                following = encode(head, stop)
                agreed = set(starts) & set(following)
                cut = next((p for p in reversed(places) if p in agreed and p > begin), None)
                if cut is not None and [s for s in starts if cut <= s < end - 1][:1] == [s for s in following if cut <= s < end - 1][:1]:
                    total += sum(s < cut for s in starts)
                    begin = cut
                    break
            if wide >= end - begin:  # no stable place in the whole chunk: take more text
                end = min(n, end + max(chunk, end - begin))
                starts, wide = encode(begin, end), overlap
            else:
                wide *= 2
        else:
            return total + len(starts)
    return total


def _count_batches(path: str, chunk: int):
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        tokenizer = load_tokenizer(path)
        for batch in batches:
            texts = [t or "" for t in batch.column(1).to_pylist()]
            counts, block, size = [0] * len(texts), [], 0

            def flush():
                if block:
                    for i, e in zip(block, tokenizer.encode_batch_fast([texts[i] for i in block], add_special_tokens=False), strict=True):
                        counts[i] = len(e)
                block.clear()

            for i, t in enumerate(texts):
                if len(t) > chunk:
                    counts[i] = count_chunked(t, tokenizer, chunk)
                elif t:
                    if size + len(t) > BATCH_CHARS:
                        flush()
                        size = 0
                    block.append(i)
                    size += len(t)
            flush()
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(counts, pa.int64())], ["doc_id", "n_bytes", "n_tokens"])

    return count


def count_tokens(docs: DataFrame, tokenizer_path: str, limit: int = 1024, chunk: int = CHUNK_CHARS) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) for each row; no begin, end or padding tokens, nothing cut off.

    ``tokenizer_path`` must be readable on every executor. Null and empty texts have no bytes and no tokens;
    repeated rows are counted each; other columns are ignored; an empty table gives an empty result.
    """
    ship_package(docs.sparkSession)
    id_type = docs.schema["doc_id"].dataType.simpleString()
    rows = docs.select("doc_id", "text", F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes"))
    counted = rows.mapInArrow(_count_batches(tokenizer_path, chunk), f"doc_id {id_type}, n_bytes long, n_tokens long")
    return counted.withColumn("over_limit", F.col("n_tokens") > limit)
