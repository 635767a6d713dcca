"""Quality rules under weak supervision, in DataFrame functions only.

Each rule looks at one measure of a text and votes bad (-1), good (+1) or abstains (0). No rule is trusted as such:
expectation-maximisation over the counts of vote patterns (at most 3 to the number of rules, whatever the corpus) estimates
how often each rule votes what on good and on bad texts, and a text's posterior probability of being good decides.
Priors of stated weight keep one frequent kind of bad text from turning the rules that it passes into evidence for all
others. What overrules them is how a rule's bad votes fall: if they are as frequent where other rules object as where none
does, the rule says nothing about quality, and its rate is taken for false alarms.

Null and empty texts have no words and fail the base rules. Very long texts are measured whole, in n log n. Repeated rows
are judged alike, extra columns are ignored, an empty table gives an empty result.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

#: What separates words, and the symbols that are counted.
BLANKS, SYMBOLS = " \t\n\x0b\f\r", "#*$%&|<>"
SEPARATOR = r"[\x20\x09-\x0D]+"
#: Rules: (name, measure, bad if, good if); the bounds are strict.
RULES: list[tuple[str, str, str, str]] = [
    ("symbols", "n_symbols / n_words", "> 0.15", "< 0.05"),
    ("repeats", "n_repeat_words / n_words", "> 0.35", "< 0.2"),
    ("capitals", "n_capitals / n_letters", "> 0.4", "< 0.2"),
    ("letters", "n_letters / word_chars", "< 0.6", "> 0.75"),
    ("exclaims", "n_exclaims / n_words", "> 0.2", "< 0.05"),
    ("dup_lines", "n_dup_lines / n_lines", "> 0.5", "< 0.3"),
    ("word_length", "abs(word_chars / n_words - 6.5)", "> 4.5", "< 3.5"),
    ("variety", "n_distinct / sqrt(n_words)", "< 2.0", "> 3.0"),
]

#: Priors: the share of bad texts, and of good ones, that get a rule's bad vote. Abstentions say nothing by themselves.
BAD_ON_BAD, BAD_ON_GOOD = 0.15, 0.001
#: Their weights, in corpora: what a class of texts has seen of a rule counts beside so many times all texts.
WEIGHT_BAD, WEIGHT_GOOD = 0.1, 20.0
#: How likely a rule is to err at random, before its votes are seen.
RANDOM_RULE = 0.05
#: Texts whose evidence for that counts at most: votes of any corpus are dependent if enough of them are looked at.
EVIDENCE_TEXTS = 20_000


def bound(value: Column, body) -> Column:
    """``body`` of a value that is computed once, for use inside lambdas."""
    return F.element_at(F.transform(F.array(value), body), 1)


def repeated_words(words: Column) -> Column:
    """Words in 3-word windows that the text has twice or more, the first ones included.

    Windows are hashed to 64 bits and sorted with their places; places of equal neighbours are covered three words each.
    """
    n = F.size(words) - 2

    def places(s: Column) -> Column:
        same = lambda k: (F.get(s, k - 1)["h"] == F.get(s, k)["h"]) | (F.get(s, k + 1)["h"] == F.get(s, k)["h"])
        hit = F.filter(F.sequence(F.lit(0), F.size(s) - 1), lambda k: F.coalesce(same(k), F.get(s, k - 1)["h"] == F.get(s, k)["h"], F.get(s, k + 1)["h"] == F.get(s, k)["h"], F.lit(False)))
        return F.sort_array(F.transform(hit, lambda k: F.get(s, k)["i"]))

    def covered(p: Column) -> Column:
        gaps = F.aggregate(F.sequence(F.lit(0), F.size(p) - 1), F.lit(0).cast("long"), lambda total, k: total + F.least(F.lit(3), F.coalesce(F.get(p, k + 1) - F.get(p, k), F.lit(3))))
        return F.when(F.size(p) == 0, F.lit(0).cast("long")).otherwise(gaps)

    def counted(h: Column) -> Column:
        placed = F.sort_array(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))
        return F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0).cast("long")).otherwise(bound(bound(placed, places), covered))

    hashes = F.transform(F.sequence(F.lit(0), n - 1), lambda i: F.xxhash64(F.get(words, i), F.get(words, i + 1), F.get(words, i + 2)))
    return F.when(n < 2, F.lit(0).cast("long")).otherwise(bound(hashes, counted))


def removed(text: Column, characters: str) -> Column:
    """How many of the characters the text has."""
    return (F.length(text) - F.length(F.translate(text, characters, ""))).cast("long")


def measures(docs: DataFrame, keep: list[str]) -> DataFrame:
    """``keep`` columns and the measures of each text, as columns of ``m``."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select(*keep, text.alias("__text"))
    words = F.filter(F.split("__text", SEPARATOR, -1), lambda w: w != "")
    lines = F.filter(F.split("__text", "\n", -1), lambda x: F.length(F.translate(x, BLANKS, "")) > 0)
    # Exploding an array of one keeps the optimizer from copying these into the lambdas and filters that use them.
    rows = rows.select(*keep, F.explode(F.array(F.struct(F.col("__text").alias("text"), words.alias("words"), lines.alias("lines")))).alias("__cut"))
    t, w, lines = F.col("__cut.text"), F.col("__cut.words"), F.col("__cut.lines")
    return rows.select(
        *keep,
        F.explode(F.array(F.struct(
            F.size(w).cast("long").alias("n_words"),
            F.length(F.translate(t, BLANKS, "")).cast("long").alias("word_chars"),
            removed(t, SYMBOLS).alias("n_symbols"),
            (F.size(lines) - F.size(F.array_distinct(lines))).cast("long").alias("n_dup_lines"),
            repeated_words(w).alias("n_repeat_words"),
            F.size(lines).cast("long").alias("n_lines"),
            removed(t, "ABCDEFGHIJKLMNOPQRSTUVWXYZÀÁÂÃÄÅÆÇÈÉÊËÌÍÎÏÑÒÓÔÕÖØÙÚÛÜÝ").alias("n_capitals"),
            F.length(F.regexp_replace(t, r"[\x00-\x40\x5B-\x60\x7B-\xA9]+", "")).cast("long").alias("n_letters"),
            removed(t, "!").alias("n_exclaims"),
            F.size(F.array_distinct(w)).cast("long").alias("n_distinct"),
        ))).alias("m"),
    )


def votes(rows: DataFrame) -> DataFrame:
    """Adds ``v``: the rules' votes as one number in base 3, and ``base_failed``."""
    m = {f: F.col(f"m.{f}") for f in rows.schema["m"].dataType.names}
    code = F.lit(0)
    for _, measure, bad, good in RULES:
        value = measure
        for name in sorted(m, key=len, reverse=True):
            value = value.replace(name, f"m.{name}") if f"m.{name}" not in value else value
        left, _, right = value.partition(" / ")
        x = value if not right else f"try_divide({left}, {right})"
        if value.startswith("abs("):
            x = "abs(try_divide(m.word_chars, m.n_words) - 6.5)"
        vote = F.expr(f"CASE WHEN {x} {bad} THEN 0 WHEN {x} {good} THEN 2 ELSE 1 END")
        code = code * 3 + vote
    failed = (m["n_words"] < 50) | (100 * m["n_repeat_words"] > 50 * m["n_words"])
    return rows.withColumn("v", code.cast("int")).withColumn("base_failed", failed)


def unpack(code: int) -> list[int]:
    """0 bad, 1 abstains, 2 good, in the order of the rules."""
    out = []
    for _ in RULES:
        out.append(code % 3)
        code //= 3
    return out[::-1]


def false_alarms(patterns: list[tuple[list[int], int]]) -> list[float]:
    """For each rule the share of good texts that it votes bad on, as far as its votes are independent of the others'.

    A rule that errs at random votes bad as often on the texts that another rule objects to as elsewhere, whichever the other
    is. One that means something has next to no bad votes there (another kind of bad text), any number (it confirms the
    other), or as many as elsewhere only if the other errs at random. The posterior probability of the first case, times the
    rule's rate, is what its false alarms come to.
    """
    out, rules = [], range(len(RULES))
    total = sum(n for _, n in patterns)
    patterns = [(p, n * min(1.0, EVIDENCE_TEXTS / max(1, total))) for p, n in patterns]
    total = sum(n for _, n in patterns)
    bad = [sum(n for p, n in patterns if p[r] == 0) for r in rules]
    for r in rules:
        rate = min(0.999, max(BAD_ON_GOOD, bad[r] / max(1, total)))
        random, useful = math.log(RANDOM_RULE), math.log(1 - RANDOM_RULE)
        for texts, both in ((bad[k], sum(n for p, n in patterns if p[k] == p[r] == 0)) for k in rules if k != r):
            ways = math.lgamma(texts + 1) - math.lgamma(both + 1) - math.lgamma(texts - both + 1)
            chance, none = (ways + both * math.log(x) + (texts - both) * math.log1p(-x) for x in (rate, BAD_ON_GOOD))
            cases = [math.log(RANDOM_RULE) + chance, math.log((1 - RANDOM_RULE) / 2) + none, math.log((1 - RANDOM_RULE) / 2) - math.log(texts + 1)]
            random += chance
            useful += max(cases) + math.log(sum(math.exp(c - max(cases)) for c in cases))
        out.append(max(BAD_ON_GOOD, rate / (1 + math.exp(min(700.0, useful - random)))))
    return out


def fit(counts: dict[int, int], rounds: int = 60) -> tuple[float, list[list[list[float]]]]:
    """(share of good texts, table[rule][class][vote]) by expectation-maximisation over pattern counts; class 1 is good.

    It starts from the rules' meaning: a pattern with a bad vote is likely bad. The priors are pseudo-counts in proportion to
    the corpus, so that the verdicts don't depend on its size.
    """
    patterns = [(unpack(c), n) for c, n in sorted(counts.items())]
    total = sum(n for _, n in patterns) + 1
    alarms = false_alarms(patterns)
    abstained = [(sum(n for p, n in patterns if p[r] == 1) + 0.2) / (sum(n for p, n in patterns if p[r] != 0) + 1) for r in range(len(RULES))]
    good = [0.1 if 0 in p else 0.95 for p, _ in patterns]
    share, table = 0.5, []
    for _ in range(rounds):
        weight = sum(n * g for g, (_, n) in zip(good, patterns, strict=True))
        share = min(0.99, max(0.01, (weight + 1) / (total + 1)))
        table = []
        for r in range(len(RULES)):
            rates = []
            for c, (prior, size) in enumerate(((BAD_ON_BAD, WEIGHT_BAD * total), (alarms[r], WEIGHT_GOOD * total))):
                own = [sum(n * (g if c else 1 - g) for g, (p, n) in zip(good, patterns, strict=True) if p[r] == v) for v in (0, 1, 2)]
                bad = (size * prior + own[0]) / (size + sum(own))
                rest = (size * abstained[r] + own[1]) / (size + own[1] + own[2])
                rates.append([bad, (1 - bad) * rest, (1 - bad) * (1 - rest)])
            table.append(rates)
        good = [posterior(p, share, table) for p, _ in patterns]
    return share, table


def posterior(pattern: list[int], share: float, table: list[list[list[float]]]) -> float:
    z = math.log(share / (1 - share)) + sum(math.log(table[r][1][v] / table[r][0][v]) for r, v in enumerate(pattern))
    return 1 / (1 + math.exp(-max(-50.0, min(50.0, z))))


def assessed(docs: DataFrame, keep: list[str]) -> DataFrame:
    """``keep`` columns, the measures, base_failed, posterior and kept.

    The measures are taken once and written to the shared folder; the pattern counts and the verdicts both read them.
    """
    rows = common.written(votes(measures(docs, keep)), "quality")
    counts = {r["v"]: r["count"] for r in rows.filter(~F.col("base_failed")).groupBy("v").count().collect()}
    share, table = fit(counts)
    z = F.lit(math.log(share / (1 - share)))
    for r in range(len(RULES)):
        vote = F.pmod(F.floor(F.col("v") / 3 ** (len(RULES) - 1 - r)), F.lit(3))
        ratio = [math.log(table[r][1][v] / table[r][0][v]) for v in (0, 1, 2)]
        z = z + F.when(vote == 0, F.lit(ratio[0])).when(vote == 1, F.lit(ratio[1])).otherwise(F.lit(ratio[2]))
    good = 1 / (1 + F.exp(-z))
    return rows.select(*keep, "m.*", "base_failed", good.alias("posterior"), (~F.col("base_failed") & (good >= 0.5)).alias("kept"))


def quality(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, posterior."""
    return assessed(docs, ["doc_id"]).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "posterior")


def kept_rows(docs: DataFrame) -> DataFrame:
    """The documents that are kept, with all their columns and no others."""
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("__row"), F.col("text"))
    return assessed(packed, ["__row"]).filter("kept").select("__row.*")
