"""Quality rules by weak supervision, in DataFrame functions only.

Each rule votes good (1), bad (-1) or abstains (0) on a document. Expectation-maximisation over the vote patterns
estimates every rule's accuracy and the share of good documents without labels, and a document is kept when its
posterior probability of being good reaches a cut. The patterns of R three-valued rules number 3**R at most, so the
table that the driver iterates over does not grow with the corpus.

Defined cases: null text counts as empty; an empty text has zero features, fails the base rules and keeps no vote but
that of length; repeated rows are judged one by one; an empty table gives an empty result. Word windows are compared
by their 64-bit hashes.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: White space between words, as a Java character class.
GAP = r"[\x20\x09-\x0D]+"
#: Characters counted as symbols.
SYMBOLS = "#*$%&|<>"
#: Up to so many distinct repeated windows are looked up one by one; beyond it, sorting marks them.
LOOKUP_LIMIT = 48


def text_features(docs: DataFrame) -> DataFrame:
    """Add the counted features of `text` to a frame; every input column stays."""
    text = F.coalesce(F.col("text"), F.lit(""))
    staged = docs.withColumn("q_words", F.filter(F.split(text, GAP), lambda w: w != ""))
    staged = staged.withColumn("q_hash", F.transform("q_words", lambda w: F.xxhash64(w)))
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    staged = (
        staged.withColumn("n_words", F.size("q_words").cast("long"))
        .withColumn("word_chars", F.length(F.regexp_replace(text, GAP, "")).cast("long"))
        .withColumn("n_symbols", (F.length(text) - F.length(F.translate(text, SYMBOLS, ""))).cast("long"))
        .withColumn("q_lines", lines)
        .withColumn("n_dup_lines", F.expr("cast(size(q_lines) - size(array_distinct(q_lines)) as bigint)"))
        .withColumn("q_n_lines", F.size("q_lines").cast("long"))
        .withColumn("q_distinct", F.expr("size(array_distinct(q_hash))").cast("long"))
        .withColumn("q_upper", (F.length(text) - F.length(F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", ""))).cast("long"))
        .withColumn("q_stress", (F.length(text) - F.length(F.translate(text, "!?", ""))).cast("long"))
        .withColumn("q_bars", (F.length(text) - F.length(F.translate(text, "|\t", ""))).cast("long"))
        .withColumn("q_stops", (F.length(text) - F.length(F.translate(text, ".,;:", ""))).cast("long"))
        .drop("q_words", "q_lines")
    )
    staged = staged.withColumn(
        "q_tri", F.expr("case when size(q_hash) < 3 then cast(array() as array<bigint>) else transform(slice(q_hash, 1, size(q_hash) - 2), (h, i) -> xxhash64(h, q_hash[i + 1], q_hash[i + 2])) end")
    ).drop("q_hash")
    staged = staged.withColumn("q_again", F.expr("case when size(array_distinct(q_tri)) = size(q_tri) then cast(array() as array<bigint>) else sort_array(q_tri) end"))
    staged = staged.withColumn("q_again", F.expr("array_distinct(filter(q_again, (x, i) -> x <=> get(q_again, i + 1)))"))
    few = f"filter(transform(q_tri, (h, i) -> if(array_contains(q_again, h), i, -1)), i -> i >= 0)"
    pairs = staged.withColumn("q_pairs", F.expr(f"case when size(q_again) > {LOOKUP_LIMIT} then sort_array(transform(q_tri, (h, i) -> named_struct('h', h, 'i', i))) end"))
    many = "sort_array(transform(filter(q_pairs, (p, j) -> p.h <=> get(q_pairs, j + 1).h or (j > 0 and p.h <=> get(q_pairs, j - 1).h)), p -> p.i))"
    placed = pairs.withColumn("q_at", F.expr(f"case when size(q_again) = 0 then cast(array() as array<int>) when size(q_again) > {LOOKUP_LIMIT} then {many} else {few} end"))
    covered = "aggregate(transform(q_at, (v, j) -> least(3, coalesce(get(q_at, j + 1) - v, 3))), 0, (a, x) -> a + x)"
    return placed.withColumn("n_repeat_words", F.expr(covered).cast("long")).drop("q_tri", "q_again", "q_pairs", "q_at")


def _band(bad: Column, good: Column) -> Column:
    return F.when(bad, -1).when(good, 1).otherwise(0)


def rules() -> dict[str, Column]:
    """The voting rules over text_features(): most look for one defect and are silent without it; three may speak for good."""
    n = F.greatest(F.col("n_words"), F.lit(1)).cast("double")
    chars = F.greatest(F.col("word_chars"), F.lit(1)).cast("double")
    lines = F.greatest(F.col("q_n_lines"), F.lit(1)).cast("double")
    enough = F.col("n_words") >= 20
    quiet = F.lit(False)
    return {
        "length": _band(F.col("n_words") < 5, F.col("n_words") >= 50),
        "sentences": _band(enough & (F.col("q_stops") == 0), enough & (F.col("q_stops") / n).between(0.02, 0.5)),
        "variety": _band(enough & (F.col("q_distinct") / n < 0.12), enough & (F.col("q_distinct") / n > 0.35)),
        "word_length": _band((F.col("word_chars") / n > 14) | (F.col("word_chars") / n < 2), quiet),
        "symbols": _band(F.col("n_symbols") / n > 0.2, quiet),
        "bars": _band(F.col("q_bars") / n > 0.2, quiet),
        "shouting": _band(F.col("q_upper") / chars > 0.4, quiet),
        "stress": _band(F.col("q_stress") / n > 0.4, quiet),
        "dup_lines": _band(enough & (F.col("n_dup_lines") / lines > 0.4), quiet),
        "repeats": _band(enough & (F.col("n_repeat_words") / n > 0.35), quiet),
    }


@dataclass(frozen=True)
class VoteModel:
    """What EM found: per rule the chance of each vote under either class, and the share of good documents."""

    names: tuple[str, ...]
    prior: float
    #: names -> ((bad, silent, good) given bad, (bad, silent, good) given good)
    table: tuple[tuple[tuple[float, float, float], tuple[float, float, float]], ...]

    def accuracy(self, k: int) -> float:
        """Chance that rule k is right when it votes."""
        bad, good = self.table[k]
        right = self.prior * good[2] + (1 - self.prior) * bad[0]
        voted = self.prior * (good[0] + good[2]) + (1 - self.prior) * (bad[0] + bad[2])
        return right / voted if voted else 0.5

    def posterior(self) -> Column:
        """Chance of good, as an expression over the vote columns v_<name>."""
        odds = F.lit(math.log(self.prior / (1 - self.prior)))
        for name, (bad, good) in zip(self.names, self.table, strict=True):
            steps = [math.log(g / b) for g, b in zip(good, bad, strict=True)]
            odds = odds + F.when(F.col(f"v_{name}") < 0, steps[0]).when(F.col(f"v_{name}") > 0, steps[2]).otherwise(0.0)
        return 1 / (1 + F.exp(-F.greatest(F.least(odds, F.lit(700.0)), F.lit(-700.0))))


def _oriented(bad: tuple[float, ...], good: tuple[float, ...]) -> tuple[tuple[float, ...], tuple[float, ...]]:
    """The same chances, with the two classes pooled for a vote that would speak against its own meaning."""
    b, g = list(bad), list(good)
    for vote, wrong in ((0, g[0] > b[0]), (2, b[2] > g[2])):
        if wrong:
            b[vote] = g[vote] = (b[vote] + g[vote]) / 2
    return tuple(x / sum(b) for x in b), tuple(x / sum(g) for x in g)


def fit_votes(patterns: list[tuple[tuple[int, ...], int]], names: tuple[str, ...], rounds: int = 60, smooth: float = 1.0) -> VoteModel:
    """EM for two classes with rules independent given the class; a silent rule is no evidence for either.

    A document with any bad vote starts as probably bad, since each rule looks for another defect and one is enough. After
    each step a rule's bad vote may not speak for good, nor its good vote for bad; so the classes cannot swap. A smoothed
    prior belief that a vote is right keeps a rule that never speaks harmless. The class balance, which votes of this kind
    don't identify, stays at the share of documents without a bad vote.
    """
    k, total = len(names), sum(n for _, n in patterns)
    prior = (sum(n for votes, n in patterns if min(votes) >= 0) + 9 * smooth) / (total + 10 * smooth)
    post = [0.04 if min(votes) < 0 else 0.96 for votes, _ in patterns]
    table: list = [((0.6, 0.3, 0.1), (0.05, 0.25, 0.7))] * k
    for _ in range(rounds):
        counts = [[[2 * smooth, smooth, smooth / 4], [smooth / 4, smooth, 2 * smooth]] for _ in range(k)]
        for p, (votes, n) in zip(post, patterns, strict=True):
            for j, v in enumerate(votes):
                counts[j][0][v + 1] += (1 - p) * n
                counts[j][1][v + 1] += p * n
        table = [_oriented(*[tuple(x / sum(row) for x in row) for row in c]) for c in counts]
        last, post = post, []
        for votes, _ in patterns:
            odds = math.log(prior / (1 - prior)) + sum(math.log(table[j][1][v + 1] / table[j][0][v + 1]) for j, v in enumerate(votes) if v)
            post.append(1 / (1 + math.exp(-max(-700.0, min(700.0, odds)))))
        if max((abs(a - b) for a, b in zip(last, post, strict=True)), default=0) < 1e-9:
            break
    return VoteModel(names, prior, tuple(table))


def with_votes(featured: DataFrame) -> DataFrame:
    return featured.withColumns({f"v_{name}": vote for name, vote in rules().items()})


def vote_patterns(voted: DataFrame) -> list[tuple[tuple[int, ...], int]]:
    """Counts by vote pattern, of which there are 3**R at most for R rules."""
    names = list(rules())
    rows = voted.groupBy(*[f"v_{n}" for n in names]).agg(F.count(F.lit(1)).alias("n")).collect()
    return sorted((tuple(int(r[f"v_{n}"]) for n in names), int(r["n"])) for r in rows)


def quality_verdicts(docs: DataFrame, materialize, cut: float = 0.5, rounds: int = 60) -> DataFrame:
    """Features, votes, posterior and verdict of each document, without its text.

    materialize(df) keeps the feature table, so that the texts are read once. The base rules (under 50 words, or more than
    half the words in repeated windows) hold whatever the votes say.
    """
    columns = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
    voted = with_votes(text_features(docs.select("doc_id", "text")))
    kept = materialize(voted.select("doc_id", *columns, *[F.col(f"v_{n}").cast("byte").alias(f"v_{n}") for n in rules()]))
    model = fit_votes(vote_patterns(kept), tuple(rules()), rounds)
    base = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return kept.select(
        "doc_id",
        *columns,
        base.alias("base_failed"),
        model.posterior().alias("posterior"),
        *[F.col(f"v_{n}").cast("int").alias(f"vote_{n}") for n in rules()],
    ).withColumn("kept", ~F.col("base_failed") & (F.col("posterior") >= cut))
