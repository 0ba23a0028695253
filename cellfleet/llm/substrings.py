"""Removal of long passages that repeat across documents, by compacting the de Bruijn graph of their words.

The graph's edges are the k-mers of ``WINDOW`` consecutive words. They aren't shuffled one by one: each has an anchor, its
``K``-word part of least hash, the leftmost of equals, which depends on the k-mer's words alone, so that equal k-mers have equal
anchors. Consecutive k-mers with one occurrence of an anchor form a run (a super-k-mer), about one for eighteen words; a run's
content is known by its first and its last k-mer, which overlap. Only anchors that occur in two documents or more go on.

A content's source is its first occurrence in the smallest document. Contents that always follow each other, and have no
other neighbour anywhere, compact to a path: each points to the one before it, and joins of pointers with pointers double their
reach until all know the head of their path. A path's occurrences elsewhere are spans, with their coordinates and the source's.
Where an anchor has several contents (the ends of passages, and edits within them), the k-mers of each content's source are
compared one by one and those that repeat form spans too. Every span is verified: its words are compared, by a 128-bit
digest of the words themselves, with those at its source's coordinates, and are left where they differ.

Until then hashes have 64 bits for words and k-mers, and k-mers and contents are compared together with their anchor's hash, that
is, by 128 bits. Null texts have no words. A null id counts as larger than any other. doc_id is a key: repeated rows get equal
results and don't remove each other's words. An empty table gives an empty result. Long texts are whole documents in one
task, and groups by document are bounded by its length. Anchors, contents and passages of very many documents are joined apart.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cellfleet.llm.common import HEAVY, cut, onto, stored, table

WINDOW, K = 50, 16
#: k-mers of a window; a run has at most as many windows, which its packed coordinates hold in the low bits.
SPREAD = WINDOW - K + 1
PACK = 64
LAST = 2**63 - 1
BASE = np.uint64(0x9E3779B97F4A7C15)


def words(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").split()


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64 bits in which every input bit moves every output bit."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def rolled(w: np.ndarray, size: int) -> np.ndarray:
    """Polynomial hash of every ``size`` consecutive values, from hashes of powers of two."""
    out, at, h, span, power = None, 0, w, 1, BASE
    n = len(w) - size + 1
    while True:
        if size & span:
            part = h[at : at + n]
            out = part.copy() if out is None else out + part * np.uint64(pow(int(BASE), at, 1 << 64))
            at += span
        if at >= size:
            return mixed(out)
        h = h[:-span] + h[span:] * power
        power, span = power * power, span * 2


def anchored(w: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(window hashes, first window of each run, last window, anchor hash) of a document of at least ``WINDOW`` words."""
    with np.errstate(over="ignore"):
        h = np.fromiter((xxhash.xxh3_64_intdigest(x) for x in w), dtype=np.uint64, count=len(w))
        kmers, windows = rolled(h, K), rolled(h, WINDOW)
    at = np.empty(len(windows), dtype=np.int64)
    step = 1 << 16
    for s in range(0, len(windows), step):
        part = kmers[s : s + step + SPREAD - 1]
        at[s : s + step] = np.lib.stride_tricks.sliding_window_view(part, SPREAD).argmin(axis=1) + np.arange(s, min(s + step, len(windows)))
    first = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]]))
    last = np.concatenate([first[1:], [len(windows)]]) - 1
    return windows, first, last, kmers[at[first]]


def content(windows: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        return mixed(windows[first] + mixed(windows[last] ^ ((last - first).astype(np.uint64) << np.uint64(56))))


def longs(x: np.ndarray) -> pa.Array:
    return pa.array(np.ascontiguousarray(x).view(np.int64), pa.int64())


def runs(docs: DataFrame) -> DataFrame:
    """(anchor, content, doc, at) of ``docs(doc, text)``; ``at`` packs the first window and the number of further ones."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            parts: list[tuple] = []
            for doc, t in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                w = words(t.as_py())
                if len(w) >= WINDOW:
                    windows, first, last, anchor = anchored(w)
                    parts.append((anchor, content(windows, first, last), np.full(len(first), doc, dtype=np.int64), first * PACK + (last - first)))
            if parts:
                yield pa.RecordBatch.from_arrays([longs(np.concatenate(c)) for c in zip(*parts, strict=True)], names=["anchor", "content", "doc", "at"])

    return docs.mapInArrow(run, "anchor bigint, content bigint, doc bigint, at bigint")


def first_window(at: Column) -> Column:
    return F.floor(at / PACK)


def last_window(at: Column) -> Column:
    return F.floor(at / PACK) + F.pmod(at, F.lit(PACK))


NODE = ["anchor", "content"]


def edges(repeated: DataFrame) -> DataFrame:
    """(anchor, content, src, src_at, last_doc, n, before, after): the distinct contents with their source and number, and the one
    content before and after them, null where they branch.

    A neighbour that isn't a repeated run, or is none, counts as a branch."""
    along = Window.partitionBy("doc").orderBy("at")
    joins = F.lag(last_window(F.col("at"))).over(along) + 1 == first_window(F.col("at"))
    leads = F.lead(first_window(F.col("at"))).over(along) == last_window(F.col("at")) + 1
    near = repeated.distinct().select("*", *[F.when(joins, F.lag(c).over(along)).otherwise(0).alias(f"b_{c}") for c in NODE], *[F.when(leads, F.lead(c).over(along)).otherwise(0).alias(f"a_{c}") for c in NODE])
    sides = [f"{side}_{c}" for side in "ba" for c in NODE]
    found = near.groupBy(*NODE).agg(
        F.min(F.struct("doc", "at")).alias("s"), F.max("doc").alias("last_doc"), F.count("*").alias("n"),
        *[f(c).alias(f"{c}{i}") for c in sides for i, f in enumerate((F.min, F.max))],
    )

    def one(side: str) -> Column:
        same = (F.col(f"{side}_anchor0") == F.col(f"{side}_anchor1")) & (F.col(f"{side}_content0") == F.col(f"{side}_content1"))
        some = (F.col(f"{side}_anchor0") != 0) | (F.col(f"{side}_content0") != 0)
        return F.when(same & some, F.struct(*[F.col(f"{side}_{c}0").alias(c) for c in NODE]))

    return found.select(*NODE, F.col("s.doc").alias("src"), F.col("s.at").alias("src_at"), "last_doc", "n", one("b").alias("before"), one("a").alias("after"))


def compacted(found: DataFrame, rows: int | None = None) -> DataFrame:
    """``found`` contents of two documents or more with ``path``: the first window, in their source, of the path they are on.

    A content whose one neighbour before has it as its one neighbour after points there. Each round, all that don't know their
    head yet take over the pointer, or the head, of what they point to: the reach doubles, and no two point to the same. A path
    begins where its source document, or the repeated part of it, does: there are no rings. ``rows``: of ``found``, if known: rounds
    are written in as few files as they need."""
    shared = found.where("last_doc > src")
    ends = shared.where("after is not null").select(F.col("after.anchor").alias("anchor"), F.col("after.content").alias("content"), F.struct("anchor", "content").alias("up"))
    joined = shared.where("before is not null").select("anchor", "content", "before").join(ends, ["anchor", "content"]).where("before = up").select("anchor", "content", "up")
    start = shared.select("anchor", "content", "src", "src_at", "n").join(joined, ["anchor", "content"], "left")
    state = stored(start.withColumn("path", F.when(F.col("up").isNull(), first_window(F.col("src_at")))), "paths", rows)
    while not state.where("up is not null").isEmpty():
        there = state.select(F.struct("anchor", "content").alias("up"), F.col("up").alias("next"), F.col("path").alias("head"))
        moved = state.where("up is not null").drop("path").join(there, "up").select("anchor", "content", "src", "src_at", "n", F.col("next").alias("up"), F.col("head").alias("path"))
        state = stored(state.where("up is null").unionByName(moved), "paths", rows)
    return state.drop("up")


def hot_keys(counted: DataFrame, key: list[str], rows: int, least: int) -> DataFrame | None:
    """The keys of ``counted(…, n)``, a count of ``rows`` rows by key, that have more than ``least`` of them."""
    return cut(counted.where(F.col("n") > least).select(*key), 1) if rows > least else None


def spans(repeated: DataFrame, paths: DataFrame, hot: DataFrame | None = None) -> DataFrame:
    """(doc, start, end, src, src_start): the words [start, end) of doc repeat those of src from src_start on."""
    hit = onto(repeated, paths.drop("n"), ["anchor", "content"], hot).where("doc > src")
    shift = first_window(F.col("at")) - first_window(F.col("src_at"))
    return (
        hit.groupBy("doc", "src", "path", shift.alias("shift"))
        .agg(F.min(first_window(F.col("at"))).alias("start"), (F.max(last_window(F.col("at"))) + WINDOW).alias("end"))
        .select("doc", "start", "end", "src", (F.col("start") - F.col("shift")).alias("src_start"))
    )


def window_rows(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """(anchor, window, doc, p): every window of the ``wanted(doc, at)`` runs, read from the documents again."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            parts: list[tuple] = []
            for doc, t, at in zip(b.column(0).to_pylist(), b.column(1), b.column(2).to_pylist(), strict=True):
                w = words(t.as_py())
                if len(w) < WINDOW:
                    continue
                windows, first, last, anchor = anchored(w)
                mine = np.flatnonzero(np.isin(first * PACK + (last - first), np.array(at, dtype=np.int64)))
                for i in mine.tolist():
                    p = np.arange(first[i], last[i] + 1)
                    parts.append((np.full(len(p), anchor[i]), windows[p], np.full(len(p), doc, dtype=np.int64), p))
            if parts:
                yield pa.RecordBatch.from_arrays([longs(np.concatenate(c)) for c in zip(*parts, strict=True)], names=["anchor", "window", "doc", "p"])

    lists = wanted.groupBy("doc").agg(F.collect_set("at").alias("at"))
    return docs.join(lists, "doc").select("doc", "text", "at").mapInArrow(run, "anchor bigint, window bigint, doc bigint, p bigint")


def told(w: list[bytes]) -> bytes:
    return hashlib.blake2b(b" ".join(w), digest_size=16).digest()


def flat(lists: pa.ListArray) -> tuple[np.ndarray, list[np.ndarray]]:
    """Where each list begins in the flattened ones, and their fields of longs; nulls are empty lists."""
    items = lists.flatten()
    sizes = lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
    return np.concatenate([[0], sizes.cumsum()]), [items.field(k).to_numpy(zero_copy_only=False) for k in range(2)]


def sources_told(docs: DataFrame, found: DataFrame) -> DataFrame:
    """(src, src_start, len, told): the digest of the words at the source's coordinates, for the different ones among ``found`` spans."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            bounds, (start, size) = flat(b.column(2))
            digests = pa.array((told(w[s : s + n]) for t, i, j in zip(b.column(1), bounds, bounds[1:], strict=False) for w in [words(t.as_py())] for s, n in zip(start[i:j].tolist(), size[i:j].tolist(), strict=True)), pa.binary())
            docs_ = np.repeat(b.column(0).to_numpy(), np.diff(bounds))
            yield pa.RecordBatch.from_arrays([pa.array(docs_), pa.array(start), pa.array(size), digests], names=["src", "src_start", "len", "told"])

    lists = found.select(F.col("src").alias("doc"), "src_start", "len").distinct().groupBy("doc").agg(F.collect_list(F.struct("src_start", "len")).alias("places"))
    # doc is a key: of rows that repeat it, one is enough
    return docs.join(lists, "doc").select("doc", "text", "places").mapInArrow(run, "src bigint, src_start bigint, len bigint, told binary").groupBy("src", "src_start", "len").agg(F.min("told").alias("told"))


def repeats(docs: DataFrame, least: int = HEAVY) -> DataFrame:
    """(doc, start, end, src, src_start, told) of ``docs(doc, text)``: ranges of words that windows of smaller documents cover,
    where these stand, and the digest of the words there. Keys of more than ``least`` rows are joined apart."""
    every = stored(runs(docs), "runs")
    rows = every.count()
    anchors = stored(every.groupBy("anchor").agg(F.min("doc").alias("d0"), F.max("doc").alias("d1"), F.count("*").alias("n")).where("d0 < d1").select("anchor", "n"), "anchors")
    hot = hot_keys(anchors, ["anchor"], rows, least)
    repeated = stored(onto(every, anchors.select("anchor"), "anchor", hot), "repeated")
    found = stored(edges(repeated), "edges")
    nodes = found.count()
    paths = compacted(found, nodes)
    whole = spans(repeated, paths, hot_keys(found, ["anchor", "content"], rows, least))
    # written, so that both sides of the join are plain exchanges
    several = stored(found.groupBy("anchor").agg(F.count("*").alias("n")).where("n > 1"), "several", nodes)
    ends = onto(found.select("anchor", "content", F.col("src").alias("doc")), several.select("anchor"), "anchor", hot_keys(several, ["anchor"], rows, least))
    wanted = repeated.join(ends, ["anchor", "content", "doc"], "left_semi").select("doc", "at")
    single = stored(window_rows(docs, wanted), "windows")
    window = ["anchor", "window"]
    least_docs = single.groupBy(*window).agg(F.min("doc").alias("src"), F.max("doc").alias("most"), F.count("*").alias("n")).where("src < most")
    least_docs = stored(least_docs.drop("most"), "firsts")
    hot_windows = hot_keys(least_docs, window, rows, least)
    single = stored(onto(single, least_docs.drop("n"), window, hot_windows), "repeated-windows")
    firsts = single.where("doc = src").groupBy(*window).agg(F.min("p").alias("src_p"))
    single = onto(single.where("doc > src"), firsts, window, hot_windows)
    # neighbouring windows with neighbouring sources as one range
    single = single.select("doc", "src", "p", (F.col("p") - F.col("src_p")).alias("shift")).distinct()
    single = single.withColumn("island", F.col("p") - F.row_number().over(Window.partitionBy("doc", "src", "shift").orderBy("p")))
    single = single.groupBy("doc", "src", "shift", "island").agg(F.min("p").alias("start"), (F.max("p") + WINDOW).alias("end"))
    found = whole.unionByName(single.select("doc", "start", "end", "src", (F.col("start") - F.col("shift")).alias("src_start")))
    found = stored(found.withColumn("len", F.col("end") - F.col("start")), "spans")
    place = ["src", "src_start", "len"]
    known = stored(sources_told(docs, found), "told")
    popular = stored(found.groupBy(*place).agg(F.count("*").alias("n")).where(F.col("n") > least), "popular") if rows > least else None
    return onto(found, known, place, None if popular is None else popular.select(*place))


def keyed(docs: DataFrame, text: str, key: str) -> DataFrame:
    return docs.select(F.coalesce(F.col(key).cast("long"), F.lit(LAST)).alias("doc"), F.col(text).alias("text"))


def remove(docs: DataFrame, text: str = "text", key: str = "doc_id", least: int = HEAVY) -> DataFrame:
    """(key, n_words, n_removed, kept_text): kept words joined by one space."""
    d = keyed(docs, text, key)
    lists = repeats(d, least).groupBy("doc").agg(F.collect_list(F.struct("start", "end", "told")).alias("gone"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            total, removed, kept = [], [], []
            (bounds, (start, end)), digests = flat(b.column(2)), b.column(2).flatten().field(2)
            for t, i, j in zip(b.column(1), bounds.tolist(), bounds[1:].tolist(), strict=False):
                w = words(t.as_py())
                total.append(len(w))
                if i < j:
                    stay = np.ones(len(w), dtype=bool)
                    for g in range(i, j):
                        if told(w[start[g] : end[g]]) == digests[g].as_py():
                            stay[start[g] : end[g]] = False
                    w = [x for x, s in zip(w, stay.tolist(), strict=True) if s]
                removed.append(total[-1] - len(w))
                kept.append(b" ".join(w).decode("utf-8", "surrogatepass"))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(total, pa.int64()), pa.array(removed, pa.int64()), pa.array(kept, pa.string())], names=["doc", "n_words", "n_removed", "kept_text"])

    out = d.join(lists, "doc", "left").select("doc", "text", "gone").mapInArrow(run, "doc bigint, n_words bigint, n_removed bigint, kept_text string")
    return out.select(F.when(F.col("doc") != LAST, F.col("doc")).alias(key), "n_words", "n_removed", "kept_text")


def op9_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "n_removed", F.sha2("kept_text", 256).alias("kept_sha256"))


ORACLE_SQL = rf"""
with d as (select doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') as w from documents),
win as (select doc_id, p, md5(array_to_string(list_slice(w, p, p + {WINDOW - 1}), ' ')) as h from (select doc_id, w, unnest(range(1, len(w) - {WINDOW - 2})) as p from d)),
least_ as (select h, min(doc_id) as m from win group by h),
gone as (select distinct doc_id, p + k as pos from win join least_ using (h), (select unnest(range({WINDOW})) as k) where doc_id > m),
word as (select doc_id, unnest(w) as x, unnest(range(1, len(w) + 1)) as pos from d),
kept as (select doc_id, count(*) as n, string_agg(x, ' ' order by pos) as t from word anti join gone using (doc_id, pos) group by doc_id)
select doc_id, len(w)::bigint as n_words, (len(w) - coalesce(n, 0))::bigint as n_removed, sha256(coalesce(t, '')) as kept_sha256 from d left join kept using (doc_id)
"""
