"""Quality rules under weak supervision: rules vote or abstain, expectation-maximisation weighs them, a posterior decides.

Each rule looks at one statistic of the whole text and votes good (1), bad (0) or abstains.  Documents can be bad in several ways that exclude each other as a
rule, so there is a class of good documents and one for every defect that rules name.  Documents are counted by vote pattern (at most 3 to the number of rules,
whatever the corpus), and expectation-maximisation over these counts estimates the shares of the classes and, for every rule, how often it votes good
on each, held to weak prior rates.  The good class is the one whose rules vote good most, so classes cannot change places.  Its posterior probability
replaces the demand that all rules pass.  SQL expressions only; each iteration is one aggregate over the pattern table.

Defined cases: null text has no words; empty tables give no rows; ties and repeated rows are judged alike; other columns are
ignored.  Where no rule votes, the posterior is the estimated share of good documents.
"""

from __future__ import annotations

from dataclasses import dataclass
from math import log

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from terse.llm.common import BLANK_CHARS, shared_folder, words, written

SYMBOLS = "#*$%&|<>"
WINDOW = 8


# fixed values: function words of the four languages of the corpus, lower case
FUNCTION_WORDS = (
    "the of and to in a is that for on with as was it by at from be this are not have or an had his which you they "
    "der die das und ist in den von zu mit sich des auf für nicht ein eine als auch es an werden aus er hat dass sie "
    "le la les de des et à en un une du que est dans qui par pour sur pas plus au il ce ne se sont avec "
    "el los las y que un una es en se no por con para del su al lo como más pero sus o"
).split()


def text_statistics(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id with n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_upper, n_distinct, n_adjacent (words equal to the one before),
    n_common (function words), n_marks (exclamation and question marks), n_lines (with a word) and n_digits of whole texts.

    Words are hashed once, and a window is the hash of its words' hashes.  Repeated windows are found by sorting (hash, position) pairs of a document; positions
    whose neighbour has the same hash are covered from there on, ``window`` words each, overlaps once.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    base = docs.select("doc_id", text.alias("text"), words(F.col("text")).alias("w"))
    base = base.withColumn("n", F.size("w")).withColumn("x", F.transform("w", lambda w: F.xxhash64(w)))
    lines = F.filter(F.split("text", "\n"), lambda x: F.trim(x, F.lit(BLANK_CHARS)) != "")
    windows = F.transform(F.sequence(F.lit(0), F.col("n") - window), lambda i: F.xxhash64(*[F.get(F.col("x"), i + k) for k in range(window)]))
    hashes = F.when(F.col("n") >= window, windows).otherwise(F.array().cast("array<bigint>"))
    without_chars = lambda chars: F.char_length("text") - F.char_length(F.translate("text", chars, ""))
    measured = base.select(
        "doc_id",
        F.col("n"),
        F.char_length(F.translate("text", BLANK_CHARS, "")).alias("word_chars"),
        without_chars(SYMBOLS).alias("n_symbols"),
        (F.size(lines) - F.size(F.array_distinct(lines))).alias("n_dup_lines"),
        F.size(lines).alias("n_lines"),
        without_chars("ABCDEFGHIJKLMNOPQRSTUVWXYZ").alias("n_upper"),
        without_chars("!?").alias("n_marks"),
        without_chars("0123456789").alias("n_digits"),
        F.size(F.array_distinct("x")).alias("n_distinct"),
        F.size(F.filter("x", lambda x, i: x == F.get(F.col("x"), i - 1))).alias("n_adjacent"),
        F.size(F.filter("w", lambda w: F.lower(w).isin(FUNCTION_WORDS))).alias("n_common"),
        hashes.alias("h"),
    )
    repeats = F.size(F.array_distinct("h")) < F.size("h")
    sorted_pairs = F.when(repeats, F.sort_array(F.transform("h", lambda x, i: F.struct(x.alias("h"), (i + 1).alias("i")))))
    paired = measured.withColumn("p", sorted_pairs)
    same = lambda i, j: F.coalesce(F.get(F.col("p"), i)["h"] == F.get(F.col("p"), j)["h"], F.lit(False))
    found = F.when(
        F.col("p").isNotNull(),
        F.sort_array(F.transform(F.filter(F.sequence(F.lit(0), F.size("p") - 1), lambda i: same(i, i - 1) | same(i, i + 1)), lambda i: F.get(F.col("p"), i)["i"])),
    ).otherwise(F.array().cast("array<int>"))
    placed = paired.withColumn("at", found)
    covered = F.aggregate(
        F.zip_with("at", F.slice("at", 2, F.greatest(F.size("at"), F.lit(1))), lambda a, b: F.least(F.lit(window), F.coalesce(b - a, F.lit(window)))),
        F.lit(0), lambda acc, x: acc + x,
    )
    names = {"n": "n_words"}
    plain = ("n", "word_chars", "n_symbols", "n_dup_lines", "n_lines", "n_upper", "n_marks", "n_digits", "n_distinct", "n_adjacent", "n_common")
    return placed.select("doc_id", *[F.col(c).cast("long").alias(names.get(c, c)) for c in plain], covered.cast("long").alias("n_repeat_words"))


@dataclass(frozen=True)
class Rule:
    """vote: 1 good, 0 bad, null for abstaining, over the statistics; defect: what kind of badness it looks for (none: any)."""

    vote: Column
    defect: str | None = None


def _vote(bad: Column, good: Column) -> Column:
    return F.when(bad, 0).when(good, 1)


def default_rules() -> dict[str, Rule]:
    """Rules by name.  Shares are of words, of characters in words or of lines; between the two bounds a rule abstains."""
    n, chars, lines = (F.greatest(F.col(c), F.lit(1)) for c in ("n_words", "word_chars", "n_lines"))
    above = lambda count, of, bad, good: _vote(count > bad * of, count <= good * of)
    return {
        "symbols": Rule(above(F.col("n_symbols"), n, 0.05, 0.01), "symbols"),
        "marks": Rule(above(F.col("n_marks"), n, 0.05, 0.01), "shouting"),
        "capitals": Rule(above(F.col("n_upper"), chars, 0.2, 0.1), "shouting"),
        "adjacent": Rule(above(F.col("n_adjacent"), n, 0.05, 0.01), "repetition"),
        "variety": Rule(_vote(F.col("n_distinct") < 0.5 * F.least(n, F.lit(300)), F.col("n_distinct") >= 0.6 * F.least(n, F.lit(300))), "repetition"),
        "repetition": Rule(above(F.col("n_repeat_words"), n, 0.1, 0.02), "repetition"),
        "duplicate_lines": Rule(above(F.col("n_dup_lines"), lines, 0.3, 0.05), "repetition"),
        "length": Rule(_vote(F.col("n_words") < 20, F.col("n_words") >= 50)),
        "function_words": Rule(_vote(F.col("n_common") < 0.08 * n, F.col("n_common") >= 0.15 * n)),
        "word_length": Rule(_vote((chars > 11 * n) | (chars < 3 * n), chars.between(3.5 * n, 8.0 * n))),
        "digits": Rule(above(F.col("n_digits"), chars, 0.1, 0.02)),
    }


@dataclass(frozen=True)
class VotePrior:
    """Where expectation-maximisation starts, and what it is held to with a weight of ``strength`` times the documents: the share of good ones, and how often a
    rule that votes votes good: on good documents, on those with its defect, on those with another defect, and, if it has none, on bad ones."""

    good: float = 0.85
    on_good: float = 0.97
    on_own: float = 0.4
    on_other: float = 0.9
    on_any: float = 0.7
    strength: float = 0.02


def start(defects: dict[str, str | None], prior: VotePrior = VotePrior()) -> tuple[list[float], list[list[float]]]:
    """Shares of the classes (good, then a class for every defect; one for all where rules name none) and, by class, each rule's rate of good votes."""
    kinds = sorted({d for d in defects.values() if d}) or [None]
    rate = lambda d, kind: prior.on_own if d == kind else prior.on_other if d else prior.on_any
    shares = [prior.good] + [(1 - prior.good) / len(kinds)] * len(kinds)
    return shares, [[prior.on_good] * len(defects)] + [[rate(d, k) for d in defects.values()] for k in kinds]


def class_weights(votes: Column, shares: list[float], rates: list[list[float]]) -> Column:
    """Probability of each class given an array of votes; an abstaining rule says nothing."""
    classes = F.array(*[F.struct(F.lit(log(p)).alias("p"), F.array(*[F.lit(log(x)) for x in r]).alias("u"), F.array(*[F.lit(log(1 - x)) for x in r]).alias("d")) for p, r in zip(shares, rates, strict=True)])
    said = lambda c, i: F.when(F.get(votes, i) == 1, F.get(c["u"], i)).when(F.get(votes, i) == 0, F.get(c["d"], i)).otherwise(0.0)
    places = F.sequence(F.lit(0), F.lit(len(rates[0]) - 1))
    likely = F.transform(classes, lambda c: F.exp(c["p"] + F.aggregate(places, F.lit(0.0), lambda acc, i: acc + said(c, i))))
    total = lambda x: F.aggregate(x, F.lit(0.0), lambda acc, y: acc + y)
    return F.transform(F.array(likely), lambda x: F.transform(x, lambda y: y / total(x)))[0]


def fit_votes(patterns: DataFrame, defects: dict[str, str | None], prior: VotePrior = VotePrior(), rounds: int = 60, tolerance: float = 1e-6) -> dict:
    """Expectation-maximisation over a written table of vote patterns (one column a rule) with counts n.

    Returns shares and rates by class and the place of the good class: the one whose rules vote good most.  Each round is one aggregate over the patterns.
    """
    names = list(defects)
    shares0, rates0 = start(defects, prior)
    shares, rates = shares0, rates0
    table = patterns.select(F.array(*[F.col(r).cast("int") for r in names]).alias("votes"), F.col("n").cast("double").alias("n"))
    total = table.agg(F.sum("n")).first()[0] or 0.0
    for _ in range(rounds if total else 0):
        part = table.withColumn("q", class_weights(F.col("votes"), shares, rates)).select("votes", "n", F.posexplode("q").alias("class", "q"))
        part = part.select("class", (F.col("n") * F.col("q")).alias("w"), F.posexplode(F.concat("votes", F.array(F.lit(1)))).alias("rule", "vote"))
        sums = {(r["class"], r["rule"], r["vote"]): r["w"] for r in part.where("vote is not null").groupBy("class", "rule", "vote").agg(F.sum("w").alias("w")).collect()}
        held = prior.strength * total
        got = lambda *key: sums.get(key, 0.0)  # noqa: B023, E731
        new = [
            [(got(k, r, 1) + held * shares0[k] * rates0[k][r]) / (got(k, r, 1) + got(k, r, 0) + held * shares0[k]) for r in range(len(names))] for k in range(len(shares))
        ]
        shares = [(got(k, len(names), 1) + held * shares0[k]) / (total + held) for k in range(len(shares))]
        moved = max(abs(a - b) for x, y in zip(new, rates, strict=True) for a, b in zip(x, y, strict=True))
        rates = new
        if moved < tolerance:
            break
    return {"shares": shares, "rates": rates, "good": max(range(len(rates)), key=lambda k: sum(rates[k])), "names": names}


def judge(docs: DataFrame, rules: dict[str, Rule] | None = None, threshold: float = 0.5) -> DataFrame:
    """doc_id, statistics, votes (vote_ and the rule's name), posterior, base_failed and kept for every document."""
    folder = shared_folder(docs.sparkSession)
    rules = rules or default_rules()
    votes = {f"vote_{name}": rule.vote for name, rule in rules.items()}
    stats = written(text_statistics(docs), folder, "statistics").withColumns(votes)
    failed = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    stats = stats.withColumn("base_failed", failed)
    patterns = written(stats.groupBy(*votes).agg(F.count("*").alias("n")), folder, "patterns")
    model = fit_votes(patterns, {f"vote_{name}": rule.defect for name, rule in rules.items()})
    good = class_weights(F.array(*[F.col(v) for v in votes]), model["shares"], model["rates"])[model["good"]]
    return stats.withColumn("posterior", good).withColumn("kept", ~F.col("base_failed") & (F.col("posterior") >= threshold))


def op10_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(spark.read.parquet(f"{sf_dir}/documents.parquet")).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "posterior"
    )
