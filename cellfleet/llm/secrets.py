"""Secret scans in DataFrame functions: fixed patterns, and character Markov models for what they miss.

Base patterns give spans in code points, leftmost and non-overlapping per kind. Besides them, runs of token characters
that no base span touches are scored by two first-order Markov models over characters, one of random strings and one of
ordinary identifiers; a run is a span of kind "random" if its mean log-likelihood ratio, or that of one of its parts between
separators, is at least ``LEAST_RATIO``, so that an ordinary name glued to a secret doesn't hide it. Runs and parts of fewer than
``LEAST_RUN`` characters tell too little and aren't scored.

The models are trained from labelled samples: random strings made by digests (labelled by construction), and tokens of
those of ``SAMPLE_DOCS`` documents, chosen by a hash of their key, that have no base span (labelled ordinary). That bound is the only
one; scans cover every document whole. Null texts are empty. Repeated rows get equal results. An empty table gives an
empty result, and models that know random strings only. Very long texts and very many spans are read within their row, in time
near to their length: places are prefix sums over blocks, overlaps are found by one merge of sorted ends, and texts are cut at
pieces of ``PIECE`` characters, never counted through from their start for each span.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cellfleet.llm.common import table

# The contract's patterns and the least characters of the group that counts.
ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
KINDS = ("assign", "access", "hex", "random")
LEAST_ASSIGNED = 12
#: Greedy runs of 16 hex digits or more, and access keys of 18 characters or more: a shorter leftmost match hides no longer one.
HEX_LONG, ACCESS_LONG = r"[0-9a-f]{16,}", r"AKIA[A-Z0-9]{14,}"

LEAST_RUN = 16
RUN = rf"[A-Za-z0-9+/_=-]{{{LEAST_RUN},}}"
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-"
SAMPLE_DOCS, SAMPLE_RANDOM, LEAST_RATIO = 1000, 2000, 1.0
BACK_OFF, MOST_STEP = 10.0, 4.0
MASK = "[SECRET]"

SPAN = "array<struct<start:int,rank:int,end:int>>"


#: Elements of a block of prefix sums, and characters of a piece of text.
BLOCK, PIECE = 64, 4096


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is worked out once a row, however often the body names it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def running(values: Column, join: Callable[[Column, Column], Column], levels: int = 2) -> Column:
    """Inclusive prefix sums (or prefix maxima, by ``join``) of an array of non-negative ints: within blocks, and over the blocks,
    so that no array of all elements is copied for each of them."""

    def plain(v: Column) -> Column:
        start = F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("out"))
        step = lambda a, x: let(join(a["at"], x), lambda y: F.struct(y.alias("at"), F.concat(a["out"], F.array(y)).alias("out")))
        return F.aggregate(v, start, step, lambda a: a["out"])

    if not levels:
        return plain(values)

    def blocked(v: Column) -> Column:
        last = F.greatest(F.ceil(F.size(v) / BLOCK).cast("int") - 1, F.lit(0))
        inner = F.transform(F.sequence(F.lit(0), last), lambda i: plain(F.slice(v, i * BLOCK + 1, BLOCK)))
        return let(inner, lambda b: let(running(F.transform(b, lambda x: F.coalesce(F.get(x, F.size(x) - 1), F.lit(0))), join, levels - 1), lambda tops: F.flatten(
            F.transform(b, lambda x, i: F.when(i == 0, x).otherwise(F.transform(x, lambda y: join(F.get(tops, i - 1), y)))))))

    return let(values, lambda v: F.when(F.size(v) <= BLOCK, plain(v)).otherwise(blocked(v)))


def matches(text: Column, pattern: str, group: int = 0, least: int = 0) -> Column:
    """Sorted (start, end, m) of the matches whose ``group`` has at least ``least`` characters. The text is cut at the matches, so
    that ends are running sums of lengths."""
    p = F.lit(pattern)
    z = F.arrays_zip(F.split(text, pattern, -1).alias("gap"), F.regexp_extract_all(text, p, F.lit(0)).alias("m"), F.regexp_extract_all(text, p, F.lit(group)).alias("v"))
    whole = "array<struct<start:int,end:int,m:string>>"

    def placed(x: Column) -> Column:
        x = F.filter(x, lambda r: r["m"].isNotNull())
        ends = lambda x: running(F.transform(x, lambda r: F.char_length(r["gap"]) + F.char_length(r["m"])), lambda a, b: a + b)
        told = lambda x: F.zip_with(ends(x), x, lambda e, r: F.struct((e - F.char_length(r["m"])).alias("start"), e.alias("end"), r["m"].alias("m"), r["v"].alias("v")))
        return F.transform(F.filter(let(x, told), lambda r: F.char_length(r["v"]) >= least), lambda r: F.struct(r["start"].alias("start"), r["end"].alias("end"), r["m"].alias("m")))

    return F.when(text.rlike(pattern), let(z, placed)).otherwise(F.array().cast(whole))


def spans_of(text: Column, pattern: str, rank: int, group: int = 0, least: int = 0) -> Column:
    found = matches(text, pattern, group, least)
    return F.when(text.rlike(pattern), F.transform(found, lambda r: F.struct(r["start"].alias("start"), F.lit(rank).alias("rank"), r["end"].alias("end")))).otherwise(F.array().cast(SPAN))


def untouched(runs: Column, base: Column) -> Column:
    """Those ``runs`` that no ``base`` span overlaps: ends of runs and starts of spans in one order, and the furthest span's end so
    far; a run's end comes before a span that starts there."""
    run_ends = F.transform(runs, lambda r: F.struct(r["end"].alias("at"), F.lit(0).alias("kind"), r["start"].alias("other"), r["m"].alias("m")))
    starts = F.transform(base, lambda s: F.struct(s["start"].alias("at"), F.lit(1).alias("kind"), s["end"].alias("other"), F.lit(None).cast("string").alias("m")))

    def merged(e: Column) -> Column:
        furthest = running(F.transform(e, lambda x: F.when(x["kind"] == 1, x["other"]).otherwise(0)), lambda a, b: F.greatest(a, b))
        free = F.filter(F.zip_with(e, furthest, lambda x, f: F.struct(x.alias("x"), f.alias("f"))), lambda z: (z["x"]["kind"] == 0) & (z["f"] <= z["x"]["other"]))
        return F.transform(free, lambda z: F.struct(z["x"]["other"].alias("start"), z["x"]["at"].alias("end"), z["x"]["m"].alias("m")))

    return F.when(F.size(base) == 0, runs).otherwise(let(F.array_sort(F.concat(run_ends, starts)), merged))


def with_base(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` with s_text and the arrays s_assign, s_access and s_hex."""
    d = docs.withColumn("s_text", F.coalesce(F.col(text), F.lit("")))
    t = F.col("s_text")
    return d.withColumn("s_assign", spans_of(t, ASSIGN, 0, 2, LEAST_ASSIGNED)).withColumn("s_access", spans_of(t, ACCESS_LONG, 1)).withColumn("s_hex", spans_of(t, HEX_LONG, 2))


def places(token: Column) -> Column:
    """Each character's place in the alphabet, 0 for any other."""
    return F.transform(F.array_remove(F.split(token, ""), ""), lambda c: F.position(c, F.lit(ALPHABET)))


def steps(at: Column) -> Column:
    """Neighbouring pairs (a, b) of an array."""
    n = F.greatest(F.size(at) - 1, F.lit(0))
    return F.arrays_zip(F.slice(at, 1, n).alias("a"), F.slice(at, 2, n).alias("b"))


def samples(docs: DataFrame, text: str = "text", key: str = "doc_id", n_docs: int = SAMPLE_DOCS, n_random: int = SAMPLE_RANDOM) -> DataFrame:
    """(random, token): digests in hexadecimal, base64 and upper-case base64, and tokens of documents without a base span."""
    made = docs.sparkSession.range(n_random).select(F.sha2(F.concat(F.lit("sample:"), F.col("id").cast("string")), 256).alias("d"))
    made = made.select(F.explode(F.array(F.substring("d", 1, 40), F.base64(F.unhex("d")), F.upper(F.base64(F.unhex("d"))))).alias("token"))
    chosen = docs.select(key).where(F.col(key).isNotNull()).distinct().orderBy(F.xxhash64(F.lit(7), key), key).limit(n_docs)
    plain = docs.join(F.broadcast(chosen), key, "left_semi").where(~F.coalesce(F.col(text), F.lit("")).rlike(f"{ASSIGN}|{ACCESS_LONG}|{HEX_LONG}"))
    told = plain.select(F.explode(F.regexp_extract_all(text, F.lit(r"[A-Za-z0-9+/_=-]{4,}"), F.lit(0))).alias("token"))
    return made.select(F.lit(True).alias("random"), "token").unionByName(told.select(F.lit(False).alias("random"), "token"))


def train(labelled: DataFrame) -> list[float]:
    """Log-ratio of the two models' chance of each character after each other, row by row, no step beyond ``MOST_STEP``.

    A model's chances of what follows a character are drawn towards its chances of characters at all, by the weight of
    ``BACK_OFF`` steps, so that characters which ordinary identifiers don't have speak for random ones wherever they stand.
    At most 2 * 68 * 68 counts reach the driver, whatever the sample."""
    size = len(ALPHABET) + 1
    pairs = labelled.select("random", F.explode(steps(places(F.col("token")))).alias("p")).groupBy("random", "p.a", "p.b").agg(F.count("*").alias("n"))
    counts = {r: [[0.0] * size for _ in range(size)] for r in (True, False)}
    for r in pairs.collect():
        counts[r["random"]][r["a"]][r["b"]] += r["n"]
    chance = {}
    for label, c in counts.items():
        each = [sum(row[j] for row in c) + 0.5 for j in range(size)]
        share = [x / sum(each) for x in each]
        chance[label] = [[(n + BACK_OFF * share[j]) / (sum(row) + BACK_OFF) for j, n in enumerate(row)] for row in c]
    return [max(-MOST_STEP, min(MOST_STEP, math.log(chance[True][i][j] / chance[False][i][j]))) for i in range(size) for j in range(size)]


def ratio(token: Column, model: list[float]) -> Column:
    """Mean log-likelihood ratio of a token's steps: above 0 it looks random."""
    table_ = F.split(F.lit(",".join(f"{x:.6f}" for x in model)), ",").cast("array<double>")
    pairs = steps(places(token))
    total = F.aggregate(pairs, F.lit(0.0), lambda acc, p: acc + F.element_at(table_, p["a"] * (len(ALPHABET) + 1) + p["b"] + 1))
    return total / F.greatest(F.char_length(token) - 1, F.lit(1))


def looks_random(run: Column, model: list[float]) -> Column:
    """Whether a run, or one of its parts between separators, is more likely under the model of random strings."""
    parts = F.filter(F.split(run, "[=/_-]+"), lambda p: F.char_length(p) >= LEAST_RUN)
    return F.exists(F.array_distinct(F.concat(F.array(run), parts)), lambda t: ratio(t, model) >= LEAST_RATIO)


def scan(docs: DataFrame, text: str = "text", key: str = "doc_id", model: list[float] | None = None) -> DataFrame:
    """``docs`` with s_text, s_assign, s_access, s_hex, and the sorted arrays s_base and s_spans of (start, rank, end)."""
    model = model or train(samples(docs, text, key))
    d = with_base(docs, text).withColumn("s_base", F.sort_array(F.concat("s_assign", "s_access", "s_hex")))
    free = untouched(matches(F.col("s_text"), RUN), F.col("s_base"))
    more = F.transform(F.filter(free, lambda c: looks_random(c["m"], model)), lambda c: F.struct(c["start"].alias("start"), F.lit(3).alias("rank"), c["end"].alias("end")))
    more = F.when(F.col("s_text").rlike(RUN), more).otherwise(F.array().cast(SPAN))
    return d.withColumn("s_spans", F.sort_array(F.concat("s_base", more)))


def told(spans: str) -> Column:
    """kind:start:end of each span, comma-joined."""
    kind = F.array(*[F.lit(k) for k in KINDS])
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", F.get(kind, s["rank"]), s["start"].cast("string"), s["end"].cast("string"))))


def masked(text: Column, spans: Column) -> Column:
    """``text`` with its sorted spans, overlapping ones as one, replaced by a mask."""

    def cut_out(pieces: Column, a: Column, b: Column) -> Column:
        i, j = F.floor(a / PIECE).cast("int"), F.floor((b - 1) / PIECE).cast("int")
        inner = F.substring(F.get(pieces, i), a % PIECE + 1, b - a)
        across = F.concat(F.substring(F.get(pieces, i), a % PIECE + 1, F.lit(PIECE)), F.array_join(F.slice(pieces, i + 2, F.greatest(j - i - 1, F.lit(0))), ""), F.substring(F.get(pieces, j), F.lit(1), (b - 1) % PIECE + 1))
        return F.when(b <= a, "").when(i == j, inner).otherwise(across)

    def gaps(s: Column, reach: Column) -> Column:
        """(a, b) of the text between spans, an empty one between two that touch; spans that begin within earlier ones have none."""
        before = lambda i: F.when(i == 0, 0).otherwise(F.get(reach, i - 1))
        each = F.transform(s, lambda x, i: F.struct(before(i).alias("a"), x["start"].alias("b")))
        inner = F.filter(each, lambda g: (g["b"] >= g["a"]))
        return F.concat(inner, F.array(F.struct(F.get(reach, F.size(reach) - 1).alias("a"), F.char_length(text).alias("b"))))

    pieces = F.regexp_extract_all(text, F.lit(rf"(?s).{{1,{PIECE}}}"), F.lit(0))
    return let(pieces, lambda p: let(spans, lambda s: let(running(F.transform(s, lambda x: x["end"]), lambda a, b: F.greatest(a, b)), lambda reach: F.array_join(
        F.transform(gaps(s, reach), lambda g: cut_out(p, g["a"], g["b"])), MASK))))


def redact(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """``docs`` in their own columns, of any names, each found span (overlapping ones as one) replaced by a mask; other texts unchanged."""
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("s_row"), F.col(text).alias("s_own"), F.col(key).alias("s_key"))
    found = F.size("s_spans") > 0
    d = scan(rows, "s_own", "s_key").withColumn("s_masked", F.when(found, masked(F.col("s_text"), F.col("s_spans"))).otherwise(F.col("s_own")))
    fresh = {text: F.col("s_masked"), "n_chars": F.when(found, F.char_length("s_masked").cast("long")).otherwise(F.col("s_row.n_chars"))}
    return d.select(*[(fresh[c] if c in fresh else F.col(f"s_row.`{c}`")).alias(c) for c in docs.columns])


def op8_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return scan(docs).select(
        "doc_id",
        *[F.size(f"s_{k}").cast("long").alias(f"n_{k}") for k in KINDS[:3]],
        F.sha2(told("s_base"), 256).alias("base_sha256"),
        told("s_spans").alias("spans"),
    )
