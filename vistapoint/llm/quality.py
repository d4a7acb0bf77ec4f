"""Quality by weak supervision: rules vote or abstain, and expectation-maximisation weighs them by estimated accuracies.

Each rule looks at one property of a text and votes good, bad or not at all. The true quality is unknown; EM finds a prior
and each rule's two accuracies (of its votes on good and on bad texts) that explain the votes best, and the posterior
probability of good decides. Votes are grouped into patterns first, of which there are at most 3^rules, so the estimation
works on a small table however many texts there are. Only DataFrame and SQL functions touch the rows.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .storage import checkpointed

SPACES = " \t\n\x0b\f\r"
SYMBOLS = "#*$%&|<>"
_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
_INDEX_BITS = 24


def let(value: Column, body) -> Column:
    """body(value) with value computed once for each row."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _count_of(text: Column, chars: str) -> Column:
    return (F.length(text) - F.length(F.translate(text, chars, ""))).cast("long")


def words_of(text: Column) -> Column:
    """The runs of characters other than space and U+0009 to U+000D."""
    trimmed = F.btrim(text, F.lit(SPACES))
    return F.when(trimmed == "", F.expr("cast(array() as array<string>)")).otherwise(F.split(trimmed, "[\\x20\\x09-\\x0D]+", -1))


def repeated_words(words: Column, index_bits: int = _INDEX_BITS) -> Column:
    """How many words lie in three-word windows that the text has twice or more.

    Window hashes are sorted with their places in the low bits, as plain integers; neighbours are compared on whole hashes.
    Where two different hashes agree in the sorted bits, so that equal ones might be parted, and where places need more
    bits, whole hashes are sorted beside their places instead, which is slower.
    """
    low = F.lit((1 << index_bits) - 1).cast("long")
    high = F.lit(-(1 << index_bits)).cast("long")

    def covered(places: Column) -> Column:
        step = lambda p, k: F.least(F.lit(3).cast("long"), F.coalesce(F.get(places, k + 1) - p, F.lit(3).cast("long")))
        return F.aggregate(F.transform(places, step), F.lit(0).cast("long"), lambda n, x: n + x)

    def total(marks: Column) -> Column:
        return let(F.sort_array(F.filter(marks, lambda x: x.isNotNull())), covered)

    def slow(hashes: Column) -> Column:
        def marked(ranked: Column) -> Column:
            other = lambda k: F.get(ranked, k)["h"]
            return total(F.transform(ranked, lambda x, k: F.when((x["h"] == other(k - 1)) | (x["h"] == other(k + 1)), x["i"])))

        return let(F.sort_array(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.cast("long").alias("i")))), marked)

    def found(hashes: Column) -> Column:
        def marked(ranked: Column) -> Column:
            whole = lambda x: F.get(hashes, x.bitwiseAND(low).cast("int"))

            def place(x: Column, k: Column) -> Column:
                own = whole(x)
                return F.when((own == whole(F.get(ranked, k - 1))) | (own == whole(F.get(ranked, k + 1))), x.bitwiseAND(low))

            def parted(x: Column, k: Column) -> Column:
                after = F.get(ranked, k + 1)
                return F.when((x.bitwiseAND(high) == after.bitwiseAND(high)) & (whole(x) != whole(after)), 1)

            fast = total(F.transform(ranked, place))
            return F.when(F.size(F.filter(F.transform(ranked, parted), lambda x: x.isNotNull())) > 0, slow(hashes)).otherwise(fast)

        packed = let(F.sort_array(F.transform(hashes, lambda h, i: h.bitwiseAND(high).bitwiseOR(i.cast("long")))), marked)
        return F.when(F.size(hashes) >= 1 << index_bits, slow(hashes)).otherwise(packed)

    def windows(w: Column) -> Column:
        return F.transform(F.sequence(F.lit(0), F.size(w) - 3), lambda i: F.xxhash64(F.get(w, i), F.get(w, i + 1), F.get(w, i + 2)))

    return F.when(F.size(words) < 3, F.lit(0).cast("long")).otherwise(let(windows(words), found))


def measures(docs: DataFrame) -> DataFrame:
    """doc_id and what the rules look at. Null texts have no words."""
    text = F.coalesce(docs["text"].cast("string"), F.lit(""))
    lines = F.filter(F.split(text, "\n", -1), lambda x: F.btrim(x, F.lit(SPACES)) != "")
    per_lines = let(lines, lambda x: F.struct(F.size(x).cast("long").alias("n_lines"), (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines")))
    per_words = let(words_of(text), lambda w: F.struct(F.size(w).cast("long").alias("n_words"), repeated_words(w).alias("n_repeat_words"), F.size(F.array_distinct(w)).cast("long").alias("n_distinct")))
    wide = docs.select("doc_id", per_words.alias("w"), per_lines.alias("l"), (F.length(F.translate(text, SPACES, ""))).cast("long").alias("word_chars"), _count_of(text, SYMBOLS).alias("n_symbols"), _count_of(text, _UPPER).alias("n_upper"), _count_of(text, ".").alias("n_stops"), _count_of(text, "!").alias("n_calls"))
    return wide.select("doc_id", "w.*", "l.*", "word_chars", "n_symbols", "n_upper", "n_stops", "n_calls")


def _bad(condition: str) -> str:
    return f"case when n_words > 0 and {condition} then 0 end"


def _between(value: str, bad: str, good: str) -> str:
    return f"case when n_words = 0 then null when {value} {bad} then 0 when {value} {good} then 1 end"


#: What each rule votes: 1 good, 0 bad, null abstains. Most only know a fault when they see it.
RULES: dict[str, str] = {
    "symbols": _bad("n_symbols > 0.2 * n_words"),
    "symbol_share": _bad("n_symbols > 0.04 * word_chars"),
    "repeats": _bad("n_repeat_words > 0.4 * n_words"),
    "lines": _bad("n_dup_lines > 0.3 * n_lines"),
    "capitals": _bad("n_upper > 0.4 * word_chars"),
    "calls": _bad("n_calls > 0.3 * n_words"),
    "variety": _between("n_distinct / n_words", "< 0.1", ">= 0.3"),
    "sentences": _between("n_words / (n_stops + 1)", "> 80", "<= 40"),
    "word_length": _between("word_chars / n_words", "not between 2.5 and 14", "between 3.5 and 10"),
    "size": _between("n_words", "< 50", ">= 80"),
}


@dataclass
class RuleModel:
    """The prior of good, and how often each rule votes 1, 0 or - on good and on bad texts."""

    prior: float
    on_good: list[dict[str, float]]
    on_bad: list[dict[str, float]]

    def log_odds(self, votes: str) -> float:
        """Of a pattern with one of 1, 0 and - for each rule."""
        return math.log(self.prior / (1 - self.prior)) + sum(math.log(g[v] / b[v]) for v, g, b in zip(votes, self.on_good, self.on_bad, strict=True))

    def accuracies(self) -> list[float]:
        """How often each rule is right when it votes."""
        out = []
        for g, b in zip(self.on_good, self.on_bad, strict=True):
            right, wrong = self.prior * g["1"] + (1 - self.prior) * b["0"], self.prior * g["0"] + (1 - self.prior) * b["1"]
            out.append(right / (right + wrong))
        return out


#: How rules are taken to vote before anything is known.
FIRST_GOOD = {"1": 0.6, "0": 0.01, "-": 0.39}
FIRST_BAD = {"1": 0.4, "0": 0.4, "-": 0.2}


def estimate(patterns: dict[str, int], rules: int, rounds: int = 200, strength: float = 10.0) -> RuleModel:
    """EM over vote patterns and their counts.

    ``strength`` pseudo-texts of each class that vote as first assumed keep each rate away from 0 and tie the label good to the votes for good.
    """
    model = RuleModel(0.8, [dict(FIRST_GOOD) for _ in range(rules)], [dict(FIRST_BAD) for _ in range(rules)])
    for _ in range(rounds):
        good, bad = strength, strength
        on_good = [{v: strength * p for v, p in FIRST_GOOD.items()} for _ in range(rules)]
        on_bad = [{v: strength * p for v, p in FIRST_BAD.items()} for _ in range(rules)]
        for votes, n in patterns.items():
            p = 1 / (1 + math.exp(-max(-700.0, min(700.0, model.log_odds(votes)))))
            good, bad = good + n * p, bad + n * (1 - p)
            for j, vote in enumerate(votes):
                on_good[j][vote] += n * p
                on_bad[j][vote] += n * (1 - p)
        after = RuleModel(good / (good + bad), [{v: x / good for v, x in r.items()} for r in on_good], [{v: x / bad for v, x in r.items()} for r in on_bad])
        change = max(abs(after.prior - model.prior), *(abs(x[v] - y[v]) for x, y in zip(after.on_good + after.on_bad, model.on_good + model.on_bad, strict=True) for v in x))
        model = after
        if change < 1e-7:
            break
    return model


def judge_quality(docs: DataFrame, rules: dict[str, str] | None = None, threshold: float = 0.5) -> DataFrame:
    """One row for each row of ``docs`` (doc_id, text): its measures, votes, quality (posterior probability of good),
    base_failed (fewer than 50 words, or over half of them in repeated windows) and kept.

    Null, empty and blank texts have no words, so the base fails. Repeated rows are judged alike; further columns are
    ignored; an empty table gives no rows.
    """
    rules = RULES if rules is None else rules
    votes = F.concat(*[F.coalesce(F.expr(f"cast(({r}) as string)"), F.lit("-")) for r in rules.values()])
    measured = checkpointed(measures(docs).withColumn("votes", votes))
    patterns = {r["votes"]: r["count"] for r in measured.groupBy("votes").count().collect()}  # at most 3^rules
    model = estimate(patterns, len(rules))
    odds = F.lit(math.log(model.prior / (1 - model.prior)))
    for j, (g, b) in enumerate(zip(model.on_good, model.on_bad, strict=True)):
        vote = F.substring("votes", j + 1, 1)
        odds = odds + F.when(vote == "1", math.log(g["1"] / b["1"])).when(vote == "0", math.log(g["0"] / b["0"])).otherwise(math.log(g["-"] / b["-"]))
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return measured.withColumns({"quality": 1 / (1 + F.exp(-odds)), "base_failed": failed}).withColumn("kept", ~F.col("base_failed") & (F.col("quality") >= threshold))
