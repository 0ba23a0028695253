"""Packing token sequences by multiway differencing.

Documents are tokenized once, whole. What fills a sequence by itself is cut off at multiples of the capacity; the tails
are cut into items of at most ``ITEM`` tokens, dealt at random into groups of bounded size, and each group is packed by
multiway differencing: of all partial partitions into k windows the two with the largest spread are merged, the fullest
window of one with the emptiest of the other, until one partition with nearly equal windows is left. k starts at the least
number that could hold the group and rises whenever a window is over capacity.

Ids are those of byte_bpe_50k.json, which knows its added token (``ADDED``) wherever a text has it. Texts may be of any
length and hold runs of any length: the rank encoder's pattern runs out of stack in white space of some hundred thousand
characters, so that long runs are cut off where the pattern ends a piece anyway, and encoded as that piece.

Only (key, start, length, checksum) of pieces is shuffled, never tokens. Null texts are empty documents: the end token
alone. Repeated rows are documents of their own. An empty table gives an empty result.
"""

from __future__ import annotations

import base64
import heapq
import re
import zlib
from collections.abc import Iterator
from functools import cache

import numpy as np
import public_tokenizers
import pyarrow as pa
import tiktoken
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellfleet.llm.common import cut, table

CAPACITY, ITEM, END = 1024, 256, 0
#: Windows that the tails of a group fill.
GROUP_WINDOWS = 128


# The added token of byte_bpe_50k.json, and the white space of the pattern.
ADDED = {"<|endoftext|>": 50256}
LONG_RUN = re.compile(r"[\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]{1024,}")
LEAST_RUN = 1024


@cache
def encoder(ranks: str) -> tiktoken.Encoding:
    """The byte-level vocabulary as ranks; its ids are those of the same vocabulary in byte_bpe_50k.json."""
    with open(ranks, "rb") as f:
        table_ = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("bytes", pat_str=public_tokenizers.PATTERN, mergeable_ranks=table_, special_tokens=ADDED)


def token_ids(text: str | None, ranks: str) -> np.ndarray:
    """Ids (unsigned 32 bits) of a whole text.

    The pattern takes a run of white space that a character follows without its last character, which may begin the next
    piece, and one that ends the text, or meets an added token, whole."""
    enc, text = encoder(ranks), text or ""
    if len(text) < LEAST_RUN or not (runs := list(LONG_RUN.finditer(text))):
        return enc.encode_to_numpy(text, allowed_special="all")
    out, at = [], 0
    for m in runs:
        ends = m.end() == len(text) or any(text.startswith(a, m.end()) for a in ADDED)
        stop = m.end() if ends else m.end() - 1
        out.append(enc.encode_to_numpy(text[at : m.start()], allowed_special="all"))
        out.append(np.array(enc._encode_single_piece(text[m.start() : stop]), dtype=np.uint32))
        at = stop
    out.append(enc.encode_to_numpy(text[at:], allowed_special="all"))
    return np.concatenate(out)


def ranks_path() -> str:
    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def cuts(n: int, capacity: int = CAPACITY, item: int = ITEM) -> list[tuple[int, int]]:
    """(start, length) of the pieces of a document of n tokens: whole sequences, then items of the tail, in even parts."""
    full = n // capacity
    out = [(i * capacity, capacity) for i in range(full)]
    start, left = full * capacity, n - full * capacity
    for parts in range(-(-left // item), 0, -1):
        take = -(-left // parts)
        out.append((start, take))
        start, left = start + take, left - take
    return out


def pieces(docs: DataFrame, text: str = "text", key: str = "doc_id", capacity: int = CAPACITY, item: int = ITEM, ranks: str | None = None) -> DataFrame:
    """(key, start, length, ids_crc32, doc_tokens, p_row): every token of every document in one piece."""
    kind, ranks = docs.schema[key].dataType.simpleString(), ranks or ranks_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        row = 0
        for b in batches:
            at, start, length, crc, total, rows = [], [], [], [], [], []
            for i, t in enumerate(b.column(1)):
                row += 1
                ids = np.append(token_ids(t.as_py(), ranks), END).astype("<u4")
                for s, n in cuts(len(ids), capacity, item):
                    at.append(i)
                    start.append(s)
                    length.append(n)
                    crc.append(zlib.crc32(ids[s : s + n].tobytes()))
                    total.append(len(ids))
                    rows.append(row)
            longs = [pa.array(x, pa.int64()) for x in (start, length, crc, total, rows)]
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at, pa.int64())), *longs], names=[key, "start", "length", "ids_crc32", "doc_tokens", "p_row"])

    return docs.select(key, text).mapInArrow(run, f"`{key}` {kind}, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, p_row bigint")


def differencing(sizes: np.ndarray, k: int) -> np.ndarray:
    """The window of each item, by merging partial partitions of k windows, the two with the largest spread first."""
    n = len(sizes)
    left, right = [-1] * n, [-1] * n  # nodes: items, then joined windows
    heap = []
    for i, s in enumerate(sizes.tolist()):
        sums, nodes = np.zeros(k, dtype=np.int64), np.full(k, -1, dtype=np.int64)
        sums[0], nodes[0] = s, i
        heap.append((-s, i, sums, nodes))
    heapq.heapify(heap)
    count = n
    while len(heap) > 1:
        _, _, sa, na = heapq.heappop(heap)
        _, _, sb, nb = heapq.heappop(heap)
        sums, other = sa + sb[::-1], nb[::-1]
        nodes = np.where(na >= 0, na, other)
        both = np.flatnonzero((na >= 0) & (other >= 0))
        if len(both):
            left.extend(na[both].tolist())
            right.extend(other[both].tolist())
            nodes[both] = np.arange(len(left) - len(both), len(left))
        order = np.argsort(-sums, kind="stable")
        sums, nodes = sums[order], nodes[order]
        sums = sums - sums[-1]
        heapq.heappush(heap, (-int(sums[0]), count, sums, nodes))
        count += 1
    out = np.full(n, -1, dtype=np.int64)
    for w, top in enumerate(heap[0][3].tolist()):
        stack = [top] if top >= 0 else []
        while stack:
            x = stack.pop()
            if x < n:
                out[x] = w
            else:
                stack += [left[x], right[x]]
    return out


def windows(sizes: np.ndarray, capacity: int = CAPACITY) -> np.ndarray:
    """The window of each item, none over capacity."""
    if not len(sizes):
        return np.zeros(0, dtype=np.int64)
    k = max(1, -(-int(sizes.sum()) // capacity))
    while True:
        out = differencing(sizes, k)
        if np.bincount(out, weights=sizes, minlength=k).max() <= capacity:
            return out
        k += 1


def pack(found: DataFrame, key: str = "doc_id", capacity: int = CAPACITY, group_windows: int = GROUP_WINDOWS) -> DataFrame:
    """``found`` pieces with sequence_id and offset. ``found`` is read twice: cut it first."""
    tails = found.where(F.col("length") < capacity).agg(F.coalesce(F.sum("length"), F.lit(0)).alias("n")).first()["n"]
    groups = max(1, -(-tails // (capacity * group_windows)))
    kind = found.schema[key].dataType.simpleString()

    def run(g: tuple[pa.Scalar, ...], t: pa.Table) -> pa.Table:
        t = t.sort_by([(c, "ascending") for c in (key, "p_row", "start", "ids_crc32")])
        size = t.column("length").to_numpy()
        full = size == capacity
        seq = np.empty(len(size), dtype=np.int64)
        seq[full] = np.arange(full.sum())
        _, window = np.unique(windows(size[~full], capacity), return_inverse=True)
        seq[~full] = full.sum() + window
        order = np.argsort(seq, kind="stable")
        run_ = size[order].cumsum() - size[order]
        first = np.searchsorted(seq[order], seq[order])
        offset = np.empty(len(size), dtype=np.int64)
        offset[order] = run_ - run_[first]
        out = t.select([key, "start", "length", "ids_crc32", "doc_tokens"])
        return out.append_column("sequence_id", pa.array(g[0].as_py() * 2**32 + seq)).append_column("offset", pa.array(offset))

    dealt = found.withColumn("p_group", F.pmod(F.xxhash64(key, "start", "ids_crc32", "p_row"), F.lit(groups)))
    return dealt.groupBy("p_group").applyInArrow(run, f"`{key}` {kind}, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, sequence_id bigint, offset bigint")


def pack_documents(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    return pack(cut(pieces(docs, text, key)), key)


def op3_pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"))
