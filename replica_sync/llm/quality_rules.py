"""Quality rules by weak supervision. DataFrame only.

Each rule votes good (1), bad (-1) or abstains (0). The votes of all rows are counted by pattern, at most
3**rules of them however many the rows, and expectation-maximisation over these counts estimates each rule's
accuracy given either class and the share of good rows. A row's posterior probability of being good decides.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from replica_sync.llm.common import kept_as_table, pick

SPACE = "[\\x20\\x09-\\x0D]+"
# Fixed value: the characters that count as symbols.
SYMBOLS = "[#*$%&|<>]"


def measured(rows: DataFrame) -> DataFrame:
    """doc_id and the base measures of each text, within one row: no exchange, n log n in the text's words.

    Windows are compared by 64-bit hashes of their three words, in sorted order, so that a text of one
    repeated word costs no more than any other.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    words = F.filter(F.split(text, SPACE), lambda w: w != "")
    lines = F.filter(F.split(text, "\n"), lambda x: F.length(F.regexp_replace(x, SPACE, "")) > 0)
    first = rows.select("doc_id", words.alias("words"), lines.alias("lines"), F.regexp_count(text, F.lit(SYMBOLS)).cast("long").alias("n_symbols"), F.length(F.regexp_replace(text, SPACE, "")).cast("long").alias("word_chars"))
    second = first.select(
        "doc_id",
        F.size("words").cast("long").alias("n_words"),
        "word_chars",
        "n_symbols",
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        F.size("lines").cast("long").alias("n_lines"),
        F.transform("words", lambda w: F.xxhash64(w)).alias("marks"),
    )
    triple = F.when(F.size("marks") >= 3, F.transform(F.slice("marks", 1, F.greatest(F.size("marks") - 2, F.lit(0))), lambda _, i: F.xxhash64(F.get("marks", i), F.get("marks", i + 1), F.get("marks", i + 2)))).otherwise(F.array().cast("array<bigint>"))
    third = second.withColumn("windows", triple).drop("marks").withColumn("sorted", F.sort_array("windows"))
    repeated = F.filter("sorted", lambda h, i: (i > 0) & (F.get("sorted", i - 1) == h))
    fourth = third.withColumn("again", F.array_distinct(repeated)).drop("sorted")
    # only texts with repeated windows go on: their windows with places, in order of the hash, flag both neighbours
    placed = F.sort_array(F.transform("windows", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    fifth = fourth.withColumn("placed", F.when(F.size("again") > 0, placed)).drop("windows", "again")
    twice = F.filter("placed", lambda x, k: (F.get("placed", k - 1)["h"] == x["h"]).eqNullSafe(True) | (F.get("placed", k + 1)["h"] == x["h"]).eqNullSafe(True))
    at = F.sort_array(F.transform(twice, lambda x: x["i"]))
    sixth = fifth.withColumn("at", at).drop("placed")
    covered = F.aggregate(F.transform("at", lambda p, k: F.least(F.lit(3), F.coalesce(F.get("at", k + 1) - p, F.lit(3)))), F.lit(0), lambda a, x: a + x)
    return sixth.withColumn("n_repeat_words", F.coalesce(covered, F.lit(0)).cast("long")).drop("at")


@dataclass(frozen=True)
class Rule:
    """Votes bad where ``bad`` holds, good where ``good`` holds, else abstains; prior: its assumed accuracy.

    A rule that finds a defect says nothing by not finding it: it has no ``good``.
    """

    name: str
    bad: Column | None = None
    good: Column | None = None
    prior: float = 0.95

    def vote(self) -> Column:
        """0 bad, 1 abstains, 2 good."""
        no = F.lit(False)
        return F.when(no if self.bad is None else self.bad, 0).when(no if self.good is None else self.good, 2).otherwise(1)

    def assumed(self) -> dict[int, tuple[float, float]]:
        """The chance of each vote given (bad, good) before any row is seen."""
        miss = 1 - self.prior
        if self.good is None:
            return {-1: (0.4, 0.4 * miss), 0: (0.599, 0.999 - 0.4 * miss), 1: (0.001, 0.001)}
        if self.bad is None:
            return {-1: (0.001, 0.001), 0: (0.999 - miss, 0.999 - self.prior), 1: (miss, self.prior)}
        return {-1: (0.6 * self.prior, 0.4 * miss), 0: (0.4, 0.3), 1: (0.6 * miss, 0.7 - 0.4 * miss)}


def standard_rules() -> list[Rule]:
    words, chars = F.col("n_words"), F.col("word_chars")
    mean = chars / F.greatest(words, F.lit(1))
    symbols = F.col("n_symbols") / F.greatest(words, F.lit(1))
    repeats = F.col("n_repeat_words") / F.greatest(words, F.lit(1))
    copies = F.col("n_dup_lines") / F.greatest(F.col("n_lines"), F.lit(1))
    return [
        Rule("short", bad=words < 20),
        Rule("mean_word", bad=(mean < 2.5) | (mean > 12)),
        Rule("symbols", bad=symbols > 0.2),
        Rule("repeats", bad=repeats > 0.3),
        Rule("line_copies", bad=copies > 0.6),
        Rule("line_words", bad=words / F.greatest(F.col("n_lines"), F.lit(1)) < 3),
        Rule("prose", good=(words >= 50) & mean.between(3, 9) & (symbols < 0.1) & (repeats < 0.3) & (copies < 0.6)),
    ]


def fitted(patterns: list[tuple[tuple[int, ...], int]], assumed: list[dict[int, tuple[float, float]]], rounds: int = 50, strength: float = 0.05) -> tuple[float, list[dict[int, tuple[float, float]]]]:
    """EM over counted vote patterns: the share of good rows, and per rule the chance of each vote given (bad, good).

    A Dirichlet prior worth the given share of all rows (20 rows at least) keeps each rule on the side that its name
    says; an empty table gives the prior.
    """
    share, chance = 0.8, assumed
    total = sum(n for _, n in patterns)
    weight_of_prior = max(20.0, strength * total)
    for _ in range(rounds if total else 0):
        weight = [(votes, n, posterior(votes, share, chance)) for votes, n in patterns]
        good = sum(n * p for _, n, p in weight)
        new = []
        for k, prior in enumerate(assumed):
            seen = {v: [weight_of_prior * prior[v][0], weight_of_prior * prior[v][1]] for v in (-1, 0, 1)}
            for votes, n, p in weight:
                seen[votes[k]][0] += n * (1 - p)
                seen[votes[k]][1] += n * p
            sums = [sum(seen[v][c] for v in seen) for c in (0, 1)]
            new.append({v: (seen[v][0] / sums[0], seen[v][1] / sums[1]) for v in seen})
        moved = abs(good / total - share)
        share, chance = min(max(good / total, 1e-3), 1 - 1e-3), new
        if moved < 1e-7:
            break
    return share, chance


def posterior(votes: tuple[int, ...], share: float, chance: list[dict[int, tuple[float, float]]]) -> float:
    odds = math.log(share / (1 - share)) + sum(math.log(c[v][1] / c[v][0]) for v, c in zip(votes, chance))
    return 1 / (1 + math.exp(-max(-700.0, min(700.0, odds))))


def judge_quality(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", rules: list[Rule] | None = None, least: float = 0.5) -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, posterior of every row.

    The only exchange counts vote patterns; their posteriors, at most 3**rules numbers, become a literal map.
    A null or empty text has no words: base_failed, not kept. Repeated rows get equal results; an empty
    table gives an empty result; other columns are not read.
    """
    rules = rules or standard_rules()
    base = kept_as_table(measured(pick(docs, doc_id=doc_id, text=text)), "quality-measures")  # each text is measured once
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    code = sum((r.vote() * 3**k for k, r in enumerate(rules)), F.lit(0))
    voted = base.withColumn("base_failed", failed).withColumn("code", code)
    counted = voted.groupBy("code").count().collect()  # at most 3**rules rows
    votes = {c: tuple(c // 3**k % 3 - 1 for k in range(len(rules))) for c, _ in counted}
    share, chance = fitted([(votes[c], n) for c, n in counted], [r.assumed() for r in rules])
    known = {c: posterior(v, share, chance) for c, v in votes.items()} or {0: 0.0}
    chosen = F.element_at(F.create_map(*[F.lit(x) for c, p in known.items() for x in (c, p)]), F.col("code"))
    out = voted.withColumn("posterior", chosen)
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", (~F.col("base_failed") & (F.col("posterior") >= least)).alias("kept"), "posterior")
