"""Token counts of the parts of documents, by offsets.

A document is encoded once, whole, since a tokenizer gives other tokens for parts alone. Each token's bytes give its span of
characters (a token of a part of a character spans that character); the spans are joined to the intervals of the parts by
binary search, and a token that meets several parts is allocated by a rule:

- ``first``: the part of its first character;
- ``last``: the part of its last character;
- ``most``: the part that holds most of its characters, the first of equals;
- ``split``: to each part by its share of the token's characters.

Parts cover the text without gaps or overlaps; a part may be empty, and then has no tokens. By lines, every line has its line
end; a text that ends in one has no empty line after it. By fields, the fields are joined by one line end, which belongs
to the field before it, and a null field is empty. Null texts are empty: one empty line, no tokens. Texts of any length are
encoded whole, in one row of one task, with an added token as one token. Repeated rows give repeated results. An empty
table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from cellfleet.llm.common import table
from cellfleet.llm.packing import ADDED, encoder, ranks_path, token_ids

RULES = ("first", "last", "most", "split")


@cache
def byte_lengths(ranks: str) -> np.ndarray:
    enc, added = encoder(ranks), {i: a for a, i in ADDED.items()}
    return np.array([len(added[i].encode() if i in added else enc.decode_single_token_bytes(i)) for i in range(enc.n_vocab)], dtype=np.int64)


def spans(text: str, ranks: str) -> tuple[np.ndarray, np.ndarray]:
    """First character of each token and the one after its last."""
    ids = token_ids(text, ranks)
    data = np.frombuffer(text.encode("utf-8", "replace"), dtype=np.uint8)
    ends = byte_lengths(ranks)[ids].cumsum()
    character = ((data & 0xC0) != 0x80).cumsum() - 1
    return character[ends - byte_lengths(ranks)[ids]], character[ends - 1] + 1


def allocate(first: np.ndarray, end: np.ndarray, bounds: np.ndarray, rule: str) -> tuple[np.ndarray, np.ndarray]:
    """(tokens, crossing tokens) of each part; part i is the characters from bounds[i] to bounds[i + 1]."""
    parts = len(bounds) - 1
    # the last part that starts at or before a character holds it: empty parts before it don't
    a = np.searchsorted(bounds, first, side="right") - 1
    b = np.searchsorted(bounds, end - 1, side="right") - 1
    crossing = np.bincount(a[a != b], minlength=parts)
    if rule in ("first", "last"):
        return np.bincount(a if rule == "first" else b, minlength=parts).astype(np.float64), crossing
    out = np.bincount(a[a == b], minlength=parts).astype(np.float64)
    for i in np.flatnonzero(a != b).tolist():  # few tokens cross a bound
        meets = np.arange(a[i], b[i] + 1)
        held = np.minimum(bounds[meets + 1], end[i]) - np.maximum(bounds[meets], first[i])
        if rule == "most":
            out[meets[held.argmax()]] += 1
        else:
            out[meets] += held / held.sum()
    return out, crossing


def line_bounds(text: str) -> np.ndarray:
    at = np.flatnonzero(np.frombuffer(text.encode("utf-32-le", "replace"), dtype="<u4") == 10) + 1
    inner = at[at < len(text)]
    return np.concatenate([[0], inner, [len(text)]])


def _counted(docs: DataFrame, key: str, columns: Sequence[str], rule: str, ranks: str | None, by_line: bool) -> DataFrame:
    if rule not in RULES:
        raise ValueError(f"rule is one of {RULES}")
    kind, ranks = docs.schema[key].dataType.simpleString(), ranks or ranks_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows: list[list] = [[] for _ in range(7)]
            for i, values in enumerate(zip(*(c.to_pylist() for c in b.columns[1:]), strict=True)):
                if by_line:
                    text = values[0] or ""
                    bounds = line_bounds(text)
                else:
                    fields = [v or "" for v in values]
                    text = "\n".join(fields)
                    bounds = np.concatenate([[0], np.cumsum([len(f) + 1 for f in fields])])
                    bounds[-1] = len(text)
                first, end = spans(text, ranks) if text else (np.zeros(0, dtype=np.int64),) * 2
                tokens, crossing = allocate(first, end, bounds, rule)
                n = len(tokens)
                for c, x in zip(rows, ([i] * n, range(n), bounds[:-1].tolist(), bounds[1:].tolist(), tokens.tolist(), crossing.tolist(), [len(first)] * n), strict=True):
                    c.extend(x)
            longs = [pa.array(c, pa.int64()) for c in (*rows[1:4], *rows[5:])]
            longs.insert(3, pa.array(rows[4], pa.float64()))
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(rows[0], pa.int64())), *longs], names=[key, "part", "start", "end", "tokens", "crossing", "doc_tokens"])

    return docs.select(key, *columns).mapInArrow(run, f"`{key}` {kind}, part bigint, start bigint, end bigint, tokens double, crossing bigint, doc_tokens bigint")


def by_line(docs: DataFrame, text: str = "text", key: str = "doc_id", rule: str = "first", ranks: str | None = None) -> DataFrame:
    """One row per line: (key, part, start, end, tokens, crossing, doc_tokens); ``crossing`` tokens start there and end later."""
    return _counted(docs, key, [text], rule, ranks, True)


def by_field(docs: DataFrame, fields: Sequence[str], key: str = "doc_id", rule: str = "first", ranks: str | None = None) -> DataFrame:
    """One row per field, in the order of ``fields``."""
    return _counted(docs, key, fields, rule, ranks, False)


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = by_line(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "part", "start", "end", found.tokens.cast("long").alias("tokens"), "crossing", "doc_tokens")
