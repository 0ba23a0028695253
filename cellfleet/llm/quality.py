"""Quality rules as weak supervision, all in DataFrame functions.

Every rule votes good (1), bad (-1) or abstains (0) on a document. Expectation-maximisation over the counts of vote
patterns (at most 3 ** rules rows, whatever the corpus) estimates how often each rule is right and how common good
documents are; a document's posterior probability of being good then decides, instead of every rule having a veto.

Null texts count as empty: no words, all rules abstain but the base ones fail. Repeated rows vote alike. An empty table
gives an empty result. Texts of any length are measured whole within their row, in time near to their length. ``keep`` takes
columns of any names; ``score`` adds ``q_`` columns to those of its input.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cellfleet.llm.common import SPACES, cut, stored, table, words

#: Base limits of the contract.
MIN_WORDS, MAX_REPEAT_PERCENT = 10, 20
WINDOW = 5
#: What is believed of rules before any document is seen: the chances of a bad vote, none and a good one on good and on bad
#: documents, and the share of good ones; it weighs as much as ``PRIOR`` of all documents, so that fits of any size are alike.
BELIEVED = {-1: (0.005, 0.30), 0: (0.145, 0.20), 1: (0.85, 0.50)}
BELIEVED_GOOD, PRIOR = 0.9, 0.02
SYMBOLS = "#*$%&|<>"
RULES = ("symbols", "capitals", "lines", "repeats", "word_length", "exclaims", "letters", "sentences", "alphabetic")


def features(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` with q_ columns: counts over the whole text, by built-in functions only.

    Repeated windows are found within the row: window hashes (64 bit) are compared as a primitive array first, and only
    documents in which two agree sort (hash, position) pairs, so work is n log n in the document's own length.
    """
    t = F.coalesce(F.col(text), F.lit(""))
    d = docs.withColumn("q_text", t).withColumn("q_words", words(F.col("q_text")))
    lines = F.filter(F.split("q_text", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    hashed = F.transform("q_words", lambda w: F.xxhash64(w))
    d = (
        d.withColumn("q_lines", lines)
        .withColumn("q_n", F.size("q_words"))
        .withColumn("q_word_hash", hashed)
        .withColumn("q_hash", F.when(F.col("q_n") >= WINDOW, F.transform(F.sequence(F.lit(1), F.col("q_n") - (WINDOW - 1)), lambda i: F.xxhash64(F.slice("q_word_hash", i, WINDOW)))).otherwise(F.array().cast("array<bigint>")))
    )
    repeated = F.size(F.array_distinct("q_hash")) < F.size("q_hash")
    d = d.withColumn("q_sorted", F.when(repeated, F.sort_array(F.transform("q_hash", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))))
    s, n = F.col("q_sorted"), F.size("q_sorted")
    same = lambda i, j: F.get(s, i)["h"] == F.get(s, j)["h"]
    at = F.filter(
        F.transform(F.sequence(F.lit(0), n - 1), lambda i: F.when(same(i, i - 1) | same(i, i + 1), F.get(s, i)["i"])),
        lambda i: i.isNotNull(),
    )
    d = d.withColumn("q_at", F.when(s.isNotNull(), F.sort_array(at)))
    start = F.struct(F.lit(-WINDOW).alias("p"), F.lit(0).alias("c"))
    covered = F.aggregate("q_at", start, lambda a, p: F.struct(p.alias("p"), (a["c"] + F.least(F.lit(WINDOW), p - a["p"])).alias("c")), lambda a: a["c"])
    no_space = F.translate("q_text", SPACES, "")
    letters = F.regexp_replace("q_text", r"[^\p{L}]+", "")
    return (
        d.withColumn("q_n_words", F.col("q_n").cast("long"))
        .withColumn("q_word_chars", F.char_length(no_space).cast("long"))
        .withColumn("q_n_symbols", (F.char_length("q_text") - F.char_length(F.translate("q_text", SYMBOLS, ""))).cast("long"))
        .withColumn("q_n_dup_lines", (F.size("q_lines") - F.size(F.array_distinct("q_lines"))).cast("long"))
        .withColumn("q_n_lines", F.size("q_lines").cast("long"))
        .withColumn("q_n_repeat_words", F.coalesce(covered, F.lit(0)).cast("long"))
        .withColumn("q_alphabetic", F.size(F.filter("q_words", lambda w: w.rlike(r"\p{L}"))).cast("long"))
        .withColumn("q_letters", F.char_length(letters).cast("long"))
        .withColumn("q_capitals", (F.char_length(letters) - F.char_length(F.regexp_replace(letters, r"\p{Lu}+", ""))).cast("long"))
        .withColumn("q_exclaims", (F.char_length("q_text") - F.char_length(F.translate("q_text", "!", ""))).cast("long"))
        .withColumn("q_stops", (F.char_length("q_text") - F.char_length(F.translate("q_text", ".?!。！？", ""))).cast("long"))
        .drop("q_text", "q_words", "q_lines", "q_n", "q_word_hash", "q_hash", "q_sorted", "q_at")
    )


def base_failed() -> Column:
    return (F.col("q_n_words") < MIN_WORDS) | (100 * F.col("q_n_repeat_words") > MAX_REPEAT_PERCENT * F.col("q_n_words"))


def votes() -> dict[str, Column]:
    """Each rule's vote; it abstains between its two limits and on documents without what it measures."""

    def rule(part: Column, whole: Column, good: Column, bad: Column) -> Column:
        return F.when(whole == 0, 0).when(bad, -1).when(good, 1).otherwise(0)

    c = {k: F.col(f"q_{k}") for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_lines", "n_repeat_words", "letters", "capitals", "exclaims", "stops", "alphabetic")}
    n, ch = c["n_words"], c["word_chars"]
    up_to = lambda part, whole, lo, hi: rule(part, whole, part <= lo * whole, part > hi * whole)
    mean = ch / F.greatest(n, F.lit(1))
    return {
        "symbols": up_to(c["n_symbols"], n, 0.02, 0.10),
        "capitals": up_to(c["capitals"], c["letters"], 0.20, 0.50),
        "lines": F.when(c["n_lines"] < 2, 0).otherwise(up_to(c["n_dup_lines"], c["n_lines"], 0.10, 0.30)),
        "repeats": up_to(c["n_repeat_words"], n, 0.05, 0.15),
        "word_length": rule(mean, n, (mean >= 3) & (mean <= 10), (mean < 2) | (mean > 15)),
        "exclaims": up_to(c["exclaims"], n, 0.05, 0.20),
        "letters": rule(c["letters"], ch, c["letters"] >= 0.85 * ch, c["letters"] < 0.70 * ch),
        "sentences": F.when(n < 30, 0).otherwise(rule(c["stops"], n, (c["stops"] >= 0.02 * n) & (c["stops"] <= 0.35 * n), c["stops"] < 0.005 * n)),
        "alphabetic": rule(c["alphabetic"], n, c["alphabetic"] >= 0.85 * n, c["alphabetic"] < 0.70 * n),
    }


def start(k: int) -> tuple[float, list[dict[int, tuple[float, float]]]]:
    return BELIEVED_GOOD, [dict(BELIEVED) for _ in range(k)]


def evidence(patterns: Sequence[tuple[Sequence[int], int]], share: float, chance: Sequence[dict[int, tuple[float, float]]]) -> float:
    """What a fit makes largest: the log-likelihood of the votes and the log of the prior density."""
    total = PRIOR * sum(n for _, n in patterns)
    out = total * (BELIEVED_GOOD * math.log(share) + (1 - BELIEVED_GOOD) * math.log(1 - share))
    out += sum(total * (BELIEVED_GOOD, 1 - BELIEVED_GOOD)[c] * BELIEVED[v][c] * math.log(row[v][c]) for row in chance for v in BELIEVED for c in (0, 1))
    for votes_, n in patterns:
        good, bad = (math.log(s) + sum(math.log(row[v][c]) for v, row in zip(votes_, chance, strict=True)) for c, s in ((0, share), (1, 1 - share)))
        top = max(good, bad)
        out += n * (top + math.log(math.exp(good - top) + math.exp(bad - top)))
    return out


def step(patterns: Sequence[tuple[Sequence[int], int]], share: float, chance: Sequence[dict[int, tuple[float, float]]]) -> tuple[float, list[dict[int, tuple[float, float]]]]:
    """One round: how good each pattern is (E), then shares of votes and classes with the prior's counts among them (M)."""
    total = sum(n for _, n in patterns)
    prior = (PRIOR * total * BELIEVED_GOOD, PRIOR * total * (1 - BELIEVED_GOOD))
    good, seen = prior[0], [{v: [prior[c] * BELIEVED[v][c] for c in (0, 1)] for v in BELIEVED} for _ in chance]
    for votes_, n in patterns:
        p = posterior(votes_, share, chance)
        good += p * n
        for row, v in zip(seen, votes_, strict=True):
            row[v][0] += n * p
            row[v][1] += n * (1 - p)
    sums = [[sum(row[v][c] for v in row) for c in (0, 1)] for row in seen]
    return good / (total + sum(prior)), [{v: (row[v][0] / t[0], row[v][1] / t[1]) for v in row} for row, t in zip(seen, sums, strict=True)]


def fit(patterns: Sequence[tuple[Sequence[int], int]], rounds: int = 500, tolerance: float = 1e-9) -> tuple[float, list[dict[int, tuple[float, float]]]]:
    """(share of good documents, {vote: (its chance on good, on bad documents)} of each rule) from (votes, count) rows.

    Expectation-maximisation for rules that vote independently given the class; a rule's good and bad votes have
    accuracies of their own, as a rule that seldom speaks up may be right whenever it does. Which of the two classes is the
    good one, and that rules are rather right than wrong, is said by Dirichlet priors alone; each rule's chances sum to one in
    each class, and no round lowers ``evidence``. No rows: what is believed before any."""
    share, chance = start(len(patterns[0][0]) if patterns else len(RULES))
    for _ in range(rounds if sum(n for _, n in patterns) else 0):
        new_share, new = step(patterns, share, chance)
        moved = max(abs(x - y) for a, b in zip(new, chance, strict=True) for v in a for x, y in zip(a[v], b[v], strict=True))
        share, chance = new_share, new
        if moved < tolerance:
            break
    return share, chance


def weight(c: dict[int, tuple[float, float]], vote: int) -> float:
    """Log-likelihood ratio of good against bad that a rule's vote adds."""
    return math.log(c[vote][0] / c[vote][1])


def posterior(v: Sequence[int], share: float, chance: Sequence[dict[int, tuple[float, float]]]) -> float:
    odds = math.log(share / (1 - share)) + sum(weight(c, x) for x, c in zip(v, chance, strict=True))
    return 1 / (1 + math.exp(-max(-700.0, min(700.0, odds))))


def patterns(voted: DataFrame) -> list[tuple[tuple[int, ...], int]]:
    """Counts of the vote patterns of all rows: at most 3 ** len(RULES) of them come to the driver."""
    cols = [f"q_vote_{r}" for r in RULES]
    return sorted((tuple(r[c] for c in cols), r["n"]) for r in voted.groupBy(*cols).agg(F.count("*").alias("n")).collect())


def with_votes(measured: DataFrame) -> DataFrame:
    return measured.withColumns({f"q_vote_{k}": v.cast("int") for k, v in votes().items()})


def probability(share: float, chance: Sequence[dict[int, tuple[float, float]]]) -> Column:
    odds = F.lit(math.log(share / (1 - share)))
    for r, c in zip(RULES, chance, strict=True):
        v = F.col(f"q_vote_{r}")
        odds = odds + F.when(v == 1, weight(c, 1)).when(v == -1, weight(c, -1)).otherwise(weight(c, 0))
    return 1 / (1 + F.exp(-odds))


def score(docs: DataFrame, text: str = "text", threshold: float = 0.5) -> DataFrame:
    """``docs`` without its text, with the q_ columns, q_probability, q_base_failed and q_kept.

    The measured rows (numbers only) are cut once; the fit and the verdict both read them."""
    measured = cut(with_votes(features(docs, text)).drop(text))
    share, chance = fit(patterns(measured))
    return (
        measured.withColumn("q_probability", probability(share, chance))
        .withColumn("q_base_failed", base_failed())
        .withColumn("q_kept", ~F.col("q_base_failed") & (F.col("q_probability") >= threshold))
    )


def keep(docs: DataFrame, text: str = "text", threshold: float = 0.5) -> DataFrame:
    """The rows of ``docs`` whose documents are kept, in their own columns; they are written once with their votes, which the fit
    and the verdict read, and never shuffled."""
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("q_row"), F.col(text).alias("q_own"))
    measured = with_votes(features(rows, "q_own")).withColumn("q_failed", base_failed())
    voted = stored(measured.select("q_row", "q_failed", *[f"q_vote_{r}" for r in RULES]), "votes")
    share, chance = fit(patterns(voted))
    return voted.where(~F.col("q_failed") & (probability(share, chance) >= threshold)).select(*[F.col(f"q_row.`{c}`").alias(c) for c in docs.columns])


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return score(docs).select(
        "doc_id",
        F.col("q_n_words").alias("n_words"),
        F.col("q_word_chars").alias("word_chars"),
        F.col("q_n_symbols").alias("n_symbols"),
        F.col("q_n_dup_lines").alias("n_dup_lines"),
        F.col("q_n_repeat_words").alias("n_repeat_words"),
        F.col("q_base_failed").alias("base_failed"),
        F.col("q_kept").alias("kept"),
    )
