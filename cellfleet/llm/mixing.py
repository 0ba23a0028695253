"""Mixing sources to target weights, by hash-random order and distributed prefix sums of sizes.

Within a source documents are ordered by a hash of their key. The hash range is cut into equal-width buckets, as many as
the source's rows ask for (hashes are even, so buckets are too, however large a source is); bucket sums are prefix-summed,
then sizes within each bucket, and every document learns where in its source's running total it stands. A source is taken
whole as often as its budget allows and the last time up to the exact budget, the document at the cut in part.

Null sources are a source of their own, the last. Null texts have size 0 and are taken 0 times. Repeated rows are
documents of their own; documents without a key are ordered by a hash of their text, so that only equal ones stand together.
An empty table, or one without a word, gives targets of 0. Documents of equal hash, key and size can't be told apart, so it
doesn't matter which of them the cut meets. Reruns agree. Columns may have any names: they travel in one struct. Texts of
any length are read within their row.
"""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cellfleet.llm.common import HEAVY, cut, heavy, onto, table, words

WEIGHTS, LIMIT, SEED = (5.0, 2.0, 1.0), 3, 1
#: Rows of a bucket, the least number of buckets of all sources together, and sources whose plan is broadcast.
BUCKET_ROWS, LEAST_BUCKETS, FEW_SOURCES = 50_000, 2048, 10_000
#: Hexadecimal digits of the hash that make a bucket, and buckets of a stretch of prefix sums.
DIGITS, STRETCH = 12, 32


def size(text: str = "text") -> Column:
    return F.size(words(F.col(text))).cast("long")


def sized(docs: DataFrame, own: bool = False, text: str = "text", key: str = "doc_id", source: str = "source", seed: int = SEED) -> DataFrame:
    """(m_key, m_source, m_size, m_hash), and with ``own`` the row itself as m_row."""
    named = F.coalesce(F.col(key).cast("string"), F.concat(F.lit("text:"), F.md5(F.coalesce(F.col(text), F.lit("")))))
    row = [F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("m_row")] if own else []
    return docs.select(
        F.col(key).alias("m_key"), F.col(source).alias("m_source"), size(text).alias("m_size"), F.md5(F.concat(F.lit(f"{seed}:"), named)).alias("m_hash"), *row
    )


def plan(rows: DataFrame, weights: Sequence[float] | Mapping[str | None, float] = WEIGHTS, limit: float = LIMIT) -> DataFrame:
    """(m_source, m_source_size, m_target, m_budget, m_buckets) for ``sized`` rows, one row per source, however many there are.

    Targets share the sum of all sizes by weight; none is above ``limit`` times its size, the excess is reshared by weight.
    Sources below their limit then all stand at one level of words per weight: with sources in order of the level at which
    they reach their limit, it is that of the first one that stays below, the highest of all such levels. ``weights``: by source (others 0), or a
    sequence that repeats over the sources in order of their code points, null last. Only the table of sources is windowed whole.
    """
    found = rows.groupBy("m_source").agg(F.sum("m_size").alias("m_source_size"), F.count("*").alias("m_n"))
    null, name = F.col("m_source").isNull(), F.col("m_source")
    if isinstance(weights, Mapping):
        known = [F.when(name.eqNullSafe(F.lit(k)), F.lit(float(w))) for k, w in weights.items()]
        weight = F.coalesce(*known, F.lit(0.0))
    else:
        place = F.row_number().over(Window.orderBy(null, name)) - 1
        weight = F.get(F.array(*[F.lit(float(w)) for w in weights]), place % len(weights))
    all_ = Window.partitionBy()
    top = F.lit(float(limit)) * F.col("m_source_size")
    w = found.withColumn("m_w", weight).withColumn("m_rows", F.sum("m_n").over(all_)).withColumn("m_total", F.sum("m_source_size").over(all_))
    w = w.withColumn("m_top", F.when(F.col("m_w") > 0, top).otherwise(0.0)).withColumn("m_cap", F.when(F.col("m_w") > 0, top / F.col("m_w")).otherwise(0.0))
    by = Window.orderBy("m_cap", null, name)
    before = F.coalesce(F.sum("m_top").over(by.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    after = F.sum("m_w").over(by.rowsBetween(Window.currentRow, Window.unboundedFollowing))
    w = w.withColumn("m_level", F.when(F.col("m_w") > 0, (F.col("m_total") - before) / after))
    below = F.col("m_level") <= F.col("m_cap")
    w = w.withColumn("m_at", F.max(F.when(below, F.col("m_level"))).over(all_)).withColumn("m_none", F.min(F.coalesce(below, F.lit(True))).over(all_))
    share = F.when(F.col("m_none"), F.col("m_total") * F.col("m_w") / F.sum("m_w").over(all_)).otherwise(F.col("m_at") * F.col("m_w"))
    target = F.when((F.col("m_source_size") == 0) | (F.col("m_w") <= 0), 0.0).when(F.coalesce(F.col("m_at") * F.col("m_w") > F.col("m_top"), F.lit(True)), F.col("m_top")).otherwise(share)
    # widths of buckets are even per source: as many buckets as its share of the rows
    wanted = F.greatest(F.lit(LEAST_BUCKETS), F.floor(F.col("m_rows") / BUCKET_ROWS))
    return w.withColumn("m_target", target).select(
        "m_source", "m_source_size", "m_target", F.floor(F.col("m_target") + 0.5).alias("m_budget"),
        F.greatest(F.lit(1), F.ceil(wanted * F.col("m_n") / F.col("m_rows"))).cast("long").alias("m_buckets"),
    )


def positions(rows: DataFrame, sources: DataFrame, few: int = FEW_SOURCES, least: int = HEAVY) -> DataFrame:
    """``sized`` rows with their source's plan, m_epochs (times the whole document is taken), m_part (words of it that are taken
    once more) and m_taken (words taken in all)."""
    # a null source can't be joined on; its place among the sources stands for it
    keyed = lambda t: t.withColumn("m_null", F.col("m_source").isNull()).withColumn("m_source", F.coalesce("m_source", F.lit("")))
    own = ["m_null", "m_source"]
    sources = cut(keyed(sources), 1)
    rows = keyed(rows)
    if sources.count() <= few:
        placed = rows.join(F.broadcast(sources), own)
    else:
        placed = onto(rows, sources, own, heavy(rows, own, rows.count(), least))
    unit = F.conv(F.substring("m_hash", 1, DIGITS), 16, 10).cast("double") / F.lit(16.0**DIGITS)
    placed = placed.withColumn("m_bucket", F.least(F.floor(unit * F.col("m_buckets")), F.col("m_buckets") - 1))
    by = [*own, "m_bucket"]
    sums = placed.groupBy(*by).agg(F.sum("m_size").alias("m_sum"))
    # prefix sums in three steps, so that no task holds all buckets of a source: over stretches of buckets, and within each
    before = lambda part, order: Window.partitionBy(*part).orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.withColumn("m_stretch", F.floor(F.col("m_bucket") / STRETCH))
    tops = sums.groupBy(*own, "m_stretch").agg(F.sum("m_sum").alias("m_total"))
    tops = tops.withColumn("m_first", F.coalesce(F.sum("m_total").over(before(own, "m_stretch")), F.lit(0))).drop("m_total")
    within = F.coalesce(F.sum("m_sum").over(before([*own, "m_stretch"], "m_bucket")), F.lit(0))
    starts = sums.withColumn("m_within", within).join(tops, [*own, "m_stretch"]).select(*by, (F.col("m_first") + F.col("m_within")).alias("m_start"))
    inside = Window.partitionBy(*by).orderBy("m_hash", "m_key", "m_size").rowsBetween(Window.unboundedPreceding, -1)
    at = placed.join(starts, by).withColumn("m_run", F.col("m_start") + F.coalesce(F.sum("m_size").over(inside), F.lit(0)))
    whole = F.when(F.col("m_source_size") > 0, F.floor(F.col("m_budget") / F.greatest(F.col("m_source_size"), F.lit(1)))).otherwise(0)
    at = at.withColumn("m_epochs", whole)
    rest = F.col("m_budget") - F.col("m_epochs") * F.col("m_source_size")
    part = F.greatest(F.lit(0), F.least(F.col("m_size"), rest - F.col("m_run")))
    at = at.withColumn("m_part", part.cast("long")).withColumn("m_taken", (F.col("m_epochs") * F.col("m_size") + F.col("m_part")).cast("long"))
    return at.withColumn("m_source", F.when(~F.col("m_null"), F.col("m_source"))).drop("m_null", "m_bucket", "m_hash", "m_start", "m_run", "m_buckets")


def mix(docs: DataFrame, weights: Sequence[float] | Mapping[str | None, float] = WEIGHTS, limit: float = LIMIT) -> DataFrame:
    """The mixed documents in their own columns, each row as often as it is taken; the last copy of a document at the cut
    has its first words only, joined by one space, and the n_chars of that text. Documents without words aren't taken."""
    rows = sized(docs, own=True)
    placed = positions(rows, plan(rows.drop("m_row"), weights, limit))
    copies = F.concat(
        F.array_repeat(F.col("m_size"), F.col("m_epochs").cast("int")),
        F.when(F.col("m_part") > 0, F.array(F.col("m_part"))).otherwise(F.array().cast("array<bigint>")),
    )
    out = placed.where("m_size > 0").withColumn("m_words", F.explode(copies))
    short = F.col("m_words") < F.col("m_size")
    text = F.when(short, F.concat_ws(" ", F.slice(words(F.col("m_row.text")), 1, F.col("m_words").cast("int")))).otherwise(F.col("m_row.text"))
    out = out.withColumn("m_text", text)
    fresh = {"text": F.col("m_text"), "n_chars": F.when(short, F.char_length("m_text").cast("long")).otherwise(F.col("m_row.n_chars"))}
    return out.select(*[(fresh[c] if c in fresh else F.col(f"m_row.`{c}`")).alias(c) for c in docs.columns])


def op1_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = cut(sized(table(spark, sf_dir, "documents")))
    at = positions(rows, plan(rows))
    return at.select(F.col("m_key").alias("doc_id"), F.col("m_size").alias("size"), F.col("m_source_size").alias("source_size"), F.col("m_target").alias("target"), F.col("m_taken").alias("taken"))


#: The same rows: weights by place, targets by the level at which the sources not at their limit share the rest, takes by running sums.
ORACLE_SQL = r"""
with d as (select doc_id, source, text, len(list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> ''))::bigint as size from documents),
s as (select source, sum(size)::bigint as source_size from d group by source),
w as (select *, case (row_number() over (order by source is null, source) - 1) % 3 when 0 then 5.0 when 1 then 2.0 else 1.0 end::double as w from s),
c as (select *, 3.0 * source_size / w as cap, sum(source_size) over () as total from w),
l as (select *, (total - coalesce(sum(3.0 * source_size) over (order by cap, source is null, source rows between unbounded preceding and 1 preceding), 0))
  / sum(w) over (order by cap, source is null, source rows between current row and unbounded following) as level from c),
v as (select max(level) filter (level <= cap) as level, sum(w) as whole from l),
t as (select l.source, source_size, case when source_size = 0 then 0.0 when v.level * w > 3 * source_size then 3.0 * source_size
  when not exists (select 1 from l x where x.level > x.cap) then total * w / v.whole else v.level * w end::double as target from l, v),
b as (select *, floor(target + 0.5)::bigint as budget from t),
r as (select d.doc_id, d.size, b.source_size, b.target, b.budget,
  coalesce(sum(d.size) over (partition by d.source order by md5('1:' || coalesce(d.doc_id::varchar, 'text:' || md5(coalesce(d.text, '')))), d.doc_id, d.size rows between unbounded preceding and 1 preceding), 0) as run
  from d join b on d.source is not distinct from b.source)
select doc_id, size, source_size, target, case when source_size = 0 then 0 else
  (budget // source_size) * size + greatest(0, least(size, budget % source_size - run)) end::bigint as taken from r
"""
