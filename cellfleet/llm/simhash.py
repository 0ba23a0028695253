"""Near-duplicates by SimHash and covering locality-sensitive hashing.

Every pair of fingerprints within the radius r agrees on the kept bits of at least one of 2 ** (r + 1) - 1 masks: bit
position i carries a vector m(i) of r + 1 bits, mask v keeps the positions where the product of v and m(i) is odd, and any
r vectors leave some v orthogonal to all of them, so that no differing position is kept by that mask.

Null and empty texts have fingerprint zero and link like any other. Repeated rows and equal texts share a fingerprint and
so a component; only distinct fingerprints enter the search, so that groups of copies cost one row. A bucket of more than
``BLOCK`` fingerprints is compared in blocks, pair of blocks by pair of blocks, none left out; each comparison emits a
spanning forest of its links and not all of them. An empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cellfleet.llm.common import HEAVY, components, cut, onto, table

RADIUS, SHINGLE, SEED, BLOCK, BITS = 3, 3, 42, 256, 64


def fingerprint(text: str | None) -> int:
    """Unsigned fingerprint of a whole text: bytes.lower and bytes.split treat A-Z and the six spaces only."""
    w = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not w:
        return 0
    shingles = [b" ".join(w[i : i + SHINGLE]) for i in range(max(1, len(w) - SHINGLE + 1))]
    h = np.fromiter((xxhash.xxh64_intdigest(s, SEED) for s in shingles), dtype="<u8", count=len(shingles))
    ones = np.zeros(BITS, dtype=np.int64)
    for i in range(0, len(h), 4096):
        ones += np.unpackbits(h[i : i + 4096].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(h), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """(key, fp): fp is the fingerprint as a signed long."""
    kind = docs.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.fromiter((fingerprint(t.as_py()) for t in b.column(1)), dtype=np.uint64, count=b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp.view(np.int64))], names=[key, "fp"])

    return docs.select(key, text).mapInArrow(run, f"`{key}` {kind}, fp bigint")


def masks(radius: int = RADIUS, bits: int = BITS) -> list[int]:
    """The covering family: 2 ** (radius + 1) - 1 masks as signed longs."""
    top = 1 << (radius + 1)
    carried = [1 + i % (top - 1) for i in range(bits)]
    out = []
    for v in range(1, top):
        mask = sum(1 << i for i, m in enumerate(carried) if (m & v).bit_count() & 1)
        out.append(mask - (1 << 64) if mask >> 63 else mask)
    return out


def forest(a: np.ndarray, b: np.ndarray | None, radius: int) -> list[tuple[int, int]]:
    """Spanning forest of the links within ``a``, or between ``a`` and ``b``."""
    both = a if b is None else np.concatenate([a, b])
    near = np.bitwise_count(both.view(np.uint64)[:, None] ^ both.view(np.uint64)[None, :]) <= radius
    left = np.ones(len(both), dtype=bool)
    out: list[tuple[int, int]] = []
    for s in range(len(both)):
        if not left[s]:
            continue
        left[s], queue = False, [s]
        while queue:
            i = queue.pop()
            new = np.flatnonzero(near[i] & left)
            left[new] = False
            queue.extend(new.tolist())
            out.extend((int(both[i]), int(both[j])) for j in new)
    return out


def _forests(radius: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found: list[tuple[int, int]] = []
            for parts in batch.column(0):
                arrays = [np.array(p, dtype=np.int64) for p in parts.as_py()]
                found += forest(arrays[0], arrays[1] if len(arrays) > 1 else None, radius)
            x = np.array(found, dtype=np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([pa.array(x[:, 0]), pa.array(x[:, 1])], names=["a", "b"])

    return run


def links(fps: DataFrame, radius: int = RADIUS, block: int = BLOCK, rows: int | None = None) -> DataFrame:
    """(a, b) links between distinct fingerprints ``fps(fp)`` within the radius, enough of them to connect all that link."""

    def apart(x: str, y: str) -> Column:
        return F.bit_count(F.col(x).bitwiseXOR(F.col(y)))

    masked = fps.select("fp", F.posexplode(F.array(*[F.col("fp").bitwiseAND(F.lit(m)) for m in masks(radius)])).alias("t", "k"))
    buckets = cut(masked.groupBy("t", "k").agg(F.count("*").alias("n"), F.min("fp").alias("a"), F.max("fp").alias("b")).where("n > 1"), rows and rows * len(masks(radius)))
    pairs = buckets.where("n = 2").where(apart("a", "b") <= radius).select("a", "b")
    large = buckets.where("n > 2").select("t", "k", F.ceil(F.col("n") / block).alias("m"))
    blocks = (
        masked.join(large, ["t", "k"])
        .groupBy("t", "k", "m", F.pmod(F.xxhash64("fp"), "m").alias("i"))
        .agg(F.sort_array(F.collect_list("fp")).alias("fps"))
    )
    met = (
        blocks.select("t", "k", "i", "fps", F.explode(F.sequence(F.lit(0).cast("long"), F.col("m") - 1)).alias("j"))
        .groupBy("t", "k", F.least("i", "j").alias("x"), F.greatest("i", "j").alias("y"))
        .agg(F.collect_set("fps").alias("parts"))
    )
    return pairs.unionByName(met.select("parts").mapInArrow(_forests(radius), "a bigint, b bigint")).distinct()


def classes(docs: DataFrame, text: str = "text", key: str = "doc_id", radius: int = RADIUS, least: int = HEAVY) -> DataFrame:
    """(key, fp, component_id): component_id is the smallest key reachable by links. Fingerprints of more than ``least``
    documents (that of all empty ones, say) are joined back apart from the rest."""
    fps = cut(fingerprints(docs, text, key))
    n = fps.count()
    distinct = cut(fps.groupBy("fp").agg(F.min(key).alias("first"), F.count("*").alias("n")), n)
    found = components(links(distinct.select("fp"), radius, rows=n), n)
    tops = distinct.join(found.select(F.col("node").alias("fp"), "component"), "fp", "left").withColumn("component", F.coalesce("component", "fp"))
    tops = cut(tops.select("fp", "first", "component"), n)
    firsts = tops.groupBy("component").agg(F.min("first").alias("component_id"), F.count("*").alias("n"))
    hot = lambda t, k: cut(t.where(F.col("n") > least).select(k), 1) if n > least else None
    by_fp = onto(tops, firsts.drop("n"), "component", hot(firsts, "component")).select("fp", "component_id")
    return onto(fps, by_fp, "fp", hot(distinct, "fp")).select(key, "fp", "component_id")


def keep_first(docs: DataFrame, text: str = "text", key: str = "doc_id", radius: int = RADIUS) -> DataFrame:
    """One document of each group, that with the smallest key; of rows that share that key one stays. Documents without a key
    can't be named by a group and stay."""
    known, unknown = docs.where(F.col(key).isNotNull()), docs.where(F.col(key).isNull())
    kept = classes(known, text, key, radius).where(F.col(key) == F.col("component_id")).select(key).distinct()
    return known.join(kept, key, "left_semi").select(*docs.columns).dropDuplicates([key]).unionByName(unknown)


def op6_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return classes(docs).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
