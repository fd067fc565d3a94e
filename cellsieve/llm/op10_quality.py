"""Quality rules as a short-circuit cascade.

Every rule is a SQL condition that holds for a bad text.  A text is rejected when any rule holds, so the order of the
rules cannot change the result, only its cost.  The order is chosen on a sample of the whole table: each rule's seconds, less those of a job without a rule, and the
sample's texts that it rejects are measured; the rule with the most rejections per second goes first, then the one with the most of what is left, and so on.  The
chosen order becomes one CASE expression, whose branches Spark evaluates only until the first that holds, with no Python and no shuffle.

Most rules count characters that prose hardly holds.  One pass over the text drops what no rule counts; the rules then count in the few characters that are left.

Definitions for odd input.  A null text, an empty one and one without any letter or digit are rejected by rule `no_words`.  A text of one good
word is kept: no rule asks for a length.  A word is a run of characters without white space (any white space ends it); of scripts that put no space
between words every character counts as one.  Null ids are judged like any other row; repeated rows are judged alike.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import written

#: Rows, about, on which costs and rejections are measured; they decide the order of the rules only.
SAMPLE_ROWS = 1_000
SAMPLE_SEED = 11
REPEATS = 2


@dataclass(frozen=True)
class Rule:
    """condition: SQL for Spark over {t}, a non-null text, and {m}, the text without DROPPED; duck: the same for DuckDB, where it differs."""

    name: str
    condition: str
    duck: str = ""


#: What no rule counts by itself: a class for the pattern that drops it.
DROPPED = r"a-z\s.,;:?'()\x22éèêëàâäùûüôöîïçñáíóúß-"


def among(chars: str) -> str:
    """SQL for the number of characters of the text that are among chars, none of which is in DROPPED."""
    return f"(length({{m}}) - length(translate({{m}}, '{chars}', '')))"


#: White space, the zero-width space among it; characters of scripts that put no space between words (Thai, Lao, Myanmar, Khmer, kana, Han of the basic plane).
BLANK = r"\s\x{1c}-\x{1f}\x{85}\x{a0}\x{1680}\x{2000}-\x{200b}\x{2028}\x{2029}\x{202f}\x{205f}\x{3000}"
JOINED = r"\x{0e00}-\x{0eff}\x{1000}-\x{109f}\x{1780}-\x{17ff}\x{3005}-\x{3007}\x{3040}-\x{30ff}\x{3400}-\x{4dbf}\x{4e00}-\x{9fff}\x{f900}-\x{faff}"
WORD = f"[{JOINED}]|[^{BLANK}{JOINED}]++"
#: A word that stands again next to itself.
ECHO = f"([{JOINED}])(?=[{BLANK}]*+\\1)|(?<![^{BLANK}{JOINED}])([^{BLANK}{JOINED}]++)(?=[{BLANK}]++\\2(?![^{BLANK}{JOINED}]))"


def occurrences(pattern: str) -> str:
    """SQL for the number of matches of the pattern in {t}."""
    return "regexp_count({t}, '" + pattern.replace("\\", "\\\\").replace("{", "{{").replace("}", "}}") + "')"


#: Texts without these characters have no white space but that of \s and no script without spaces; on them simpler patterns count the same, much faster.
OTHER = r"[\x{1c}-\x{1f}\x{85}\x{a0}\x{0e00}-\x{ffff}]"


UNUSUAL = occurrences(OTHER).replace("regexp_count", "regexp_like")
WORDS = f"(CASE WHEN {UNUSUAL} THEN {occurrences(WORD)} ELSE {occurrences('[^ ]++').replace('[^ ]', chr(92) * 2 + 'S')} END)"
#: Both counts of a text of usual characters in one walk over its words.
PLAIN_ECHOES = (
    r"aggregate(split({t}, '\\s+'), struct('' AS last, 0 AS echoes, 0 AS words), "
    "(s, x) -> struct(x AS last, s.echoes + int(x = s.last AND x <> '') AS echoes, s.words + int(x <> '') AS words), s -> s.words >= 8 AND s.echoes * 5 > s.words)"
)
#: The same words by RE2, which knows no possessive runs and needs none here; \\v is white space here and not there.
DUCK_LIST = "regexp_extract_all({t}, '" + f"[{JOINED}]|[^{BLANK}{JOINED}]+".replace(r"\s", r"\s\x{0b}").replace("{", "{{").replace("}", "}}") + "')"
DUCK_WORDS = f"len({DUCK_LIST})"
CAPITALS = among("ABCDEFGHIJKLMNOPQRSTUVWXYZÀÁÂÄÇÈÉÊÍÑÓÔÖÚÜ")
DUCK_ECHOES = f"len(list_filter(list_zip({DUCK_LIST}, {DUCK_LIST}[2:]), lambda x: coalesce(x[1] = x[2], false)))"
DOTS = "(length({t}) - length(replace({t}, '...', '')))"


def dense(name: str, marks: str, tenths: int, least: int) -> Rule:
    """At least so many marks, and more than so many tenths of the words."""
    share = "" if tenths == 1 else f" * {tenths}"
    return Rule(name, f"{marks} >= {least} AND {marks} * 10 > {WORDS}{share}", f"{marks} * 10 > {DUCK_WORDS}{share} AND {marks} >= {least}")


RULES = (
    Rule("no_words", "NOT {t} rlike '[\\\\p{{L}}\\\\p{{N}}]'", "NOT regexp_matches({t}, '[\\p{{L}}\\p{{N}}]')"),
    # marks that prose hardly holds, cells of tables and link lists, shouting: against words, which are counted only where there are marks enough
    dense("symbols", among("#$%&*^~"), 3, 4),
    dense("bars", among("|"), 1, 2),
    dense("exclamations", among("!"), 4, 4),
    dense("braces", among("{}<>").replace("{}<>", "{{}}<>"), 4, 6),
    Rule("capitals", f"{CAPITALS} * 10 > length({{t}}) * 5 AND length({{t}}) >= 40"),
    Rule("digits", f"{among('0123456789')} * 10 > length({{t}}) * 5 AND length({{t}}) >= 40"),
    Rule("ellipses", f"{DOTS} >= 12 AND {DOTS} * 2 > {WORDS} * 3", f"{DOTS} * 2 > {DUCK_WORDS} * 3 AND {DOTS[1:-1]} >= 12"),
    # a word that follows itself: more than a fifth of at least 8 words
    Rule("echoes", f"CASE WHEN {UNUSUAL} THEN {occurrences(WORD)} >= 8 AND {occurrences(ECHO)} * 5 > {occurrences(WORD)} ELSE {PLAIN_ECHOES} END", f"{DUCK_WORDS} >= 8 AND {DUCK_ECHOES} * 5 > {DUCK_WORDS}"),
)


def condition(rule: Rule, text: str = "text", duck: bool = False) -> str:
    """The rule over a column, for Spark with MARKS beside it; a null text holds for no_words alone."""
    t, m = (f'"{text}"',) * 2 if duck else (f"`{text}`", f"`{MARKS}`")
    return f"coalesce({(rule.duck if duck and rule.duck else rule.condition).format(t=t, m=m)}, {str(rule.name == 'no_words').lower()})"


MARKS = "__cellsieve_marks"


def with_marks(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs with MARKS, the text without DROPPED.  A generator makes it, so that Catalyst can't put its expression into each of the rules."""
    return docs.select("*", F.explode(F.array(F.regexp_replace(F.col(text_col).cast("string"), f"[{DROPPED}]++", ""))).alias(MARKS))


def measured(docs: DataFrame, text_col: str = "text", rules: tuple[Rule, ...] = RULES, rows: int = SAMPLE_ROWS) -> tuple[dict[Rule, float], list[tuple[bool, ...]]]:
    """(seconds a row of each rule, for each sampled row which rules hold) on about `rows` rows of the whole table."""
    texts = docs.select(F.col(text_col).cast("string").alias("text"))
    n = docs.count()
    if not n:
        return dict.fromkeys(rules, 1.0), []
    share = 1.25 * rows / n
    sample = with_marks(written((texts.sample(share, SAMPLE_SEED) if share < 1 else texts).repartition(1), "quality-sample"))
    hits = [tuple(r) for r in sample.select(*[F.expr(condition(r)) for r in rules]).collect()]

    def seconds(condition_: str) -> float:
        best = float("inf")
        for _ in range(REPEATS):
            began = time.perf_counter()
            sample.select(F.expr(condition_)).write.format("noop").mode("overwrite").save()
            best = min(best, time.perf_counter() - began)
        return best

    base = seconds(f"length({MARKS}) < 0")
    return {r: max(seconds(condition(r)) - base, 1e-5) / max(1, len(hits)) for r in rules}, hits


def ordered(costs: dict[Rule, float], hits: list[tuple[bool, ...]], rules: tuple[Rule, ...] = RULES) -> tuple[Rule, ...]:
    """Rules by rejection per cost among the sampled rows that the rules before them keep; those that reject nothing more come last, the cheaper first, then by name."""
    out: list[Rule] = []
    left = list(range(len(rules)))
    while left:
        best = min(left, key=lambda k: (-sum(h[k] for h in hits) / costs[rules[k]], costs[rules[k]], rules[k].name))
        out.append(rules[best])
        left.remove(best)
        hits = [h for h in hits if not h[best]]
    return tuple(out)


def cascade(rules: tuple[Rule, ...], text_col: str = "text") -> Column:
    """True where any rule holds, over rows with MARKS; later rules are not evaluated once one holds."""
    out = F.when(F.expr(condition(rules[0], text_col)), True)
    for r in rules[1:]:
        out = out.when(F.expr(condition(r, text_col)), True)
    return out.otherwise(False)


def judged(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """(doc_id, keep, failed): failed names, in alphabetical order, all rules that hold, joined by commas; it is computed for rejected rows alone."""
    bad = cascade(ordered(*measured(docs, text_col, rules), rules))
    names = F.concat_ws(",", *[F.when(F.expr(condition(r, "text")), F.lit(r.name)) for r in sorted(rules, key=lambda r: r.name)])
    src = with_marks(docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"))).withColumn("bad", bad)
    return src.select("doc_id", (~F.col("bad")).alias("keep"), F.when(F.col("bad"), names).otherwise("").alias("failed"))


def judged_sql(rules: tuple[Rule, ...] = RULES) -> str:
    any_rule = " OR ".join(condition(r, duck=True) for r in rules)
    names = ", ".join(f"CASE WHEN {condition(r, duck=True)} THEN '{r.name}' END" for r in sorted(rules, key=lambda r: r.name))
    return f"SELECT doc_id, NOT ({any_rule}) AS keep, CASE WHEN {any_rule} THEN concat_ws(',', {names}) ELSE '' END AS failed FROM documents"


def filter_documents(docs: DataFrame, text_col: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """The rows of docs that no rule rejects, all columns as they were."""
    return with_marks(docs, text_col).where(~cascade(ordered(*measured(docs, text_col, rules), rules), text_col)).drop(MARKS)
