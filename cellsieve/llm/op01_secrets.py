"""Secret scans: keyword automaton, anchored patterns only at its hits, then checks that the secret itself carries.

One Aho-Corasick pass over the lower-cased text finds keywords; only where one stands is that keyword's pattern matched, anchored at
the keyword, so a text without keywords costs one pass.  A match must then pass its rule's check: the CRC32 that
GitHub and npm tokens end with, a JSON header in web tokens, the spread of characters in values of assignments.  Every pattern reads a bounded stretch,
or one that ends where the keyword stands next, so a text costs its length, however many keywords it holds.

Not found: secrets without a prefix that is known here, a word of assignment before them, or a check; values of assignments without both a letter and
a digit, or longer than MAX_VALUE; passwords that hold a quote, a bracket, a comma or a semicolon and are not quoted.  A private key's
first line alone, with no key after it, is no secret.

Definitions for odd input.  Null and empty texts hold nothing.  Offsets count characters of the whole text, which is never cut; `stop` is
exclusive.  Where matches overlap, the rule that stands first in RULES wins, then the longer match, then the earlier.  Repeated
rows repeat their findings; a null id stays null.
"""

from __future__ import annotations

import base64
import binascii
import hashlib
import json
import math
import re
from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import lru_cache

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks, disjoint, lowered

BASE62 = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"
#: Bits a character that the value of an assignment needs, its least length (of passwords: MIN_PASSWORD), and the longest that is a key and not data.
MIN_BITS = 2.5
MIN_VALUE = 12
MIN_PASSWORD = 8
MAX_VALUE = 512


def crc_tail(secret: str) -> bool:
    """The last six characters are the CRC32, in base 62, of those between the prefix and them."""
    body, tail = secret.partition("_")[2][:-6], secret[-6:]
    n, out = binascii.crc32(body.encode()), ""
    while n:
        n, r = divmod(n, 62)
        out = BASE62[r] + out
    return out.rjust(6, "0") == tail


def json_header(secret: str) -> bool:
    head = secret.split(".")[0]
    try:
        found = json.loads(base64.urlsafe_b64decode(head + "=" * (-len(head) % 4)))
    except (ValueError, binascii.Error):
        return False
    return isinstance(found, dict) and "alg" in found


def spread(value: str) -> bool:
    n = len(value)
    bits = -sum(c / n * math.log2(c / n) for c in Counter(value).values())
    return bits >= MIN_BITS and any(c.isdigit() for c in value) and any(c.isalpha() for c in value)


def always(_: str) -> bool:
    return True


@dataclass(frozen=True)
class Rule:
    """pattern matches at the keyword (`before` characters earlier at most start a match); its group `s`, or all, is the secret."""

    name: str
    keywords: tuple[str, ...]
    pattern: str
    check: Callable[[str], bool] = always


END = r"(?![A-Za-z0-9_])"
KEY = r"(?:[A-Z0-9]++ )*PRIVATE KEY(?: BLOCK)?-----"
WORDS = r"(?i:token|secret|api[_-]?key|access_key|private_key|credentials?)"
PASSWORDS = r"(?i:password|passwd|pwd)"
#: Between an assignment's name and its value.
GIVEN = r"[\w-]{0,30}[\"']?\s{0,4}(?::=|=>|=|:)\s{0,4}"
RULES = (
    # up to its end line, which is the next row of five dashes; where that is missing, as in a text that was cut, the lines of base 64 after the first line
    Rule("private_key", ("-----begin ",), rf"-----BEGIN {KEY}(?:[^-]*+(?:-(?!----)[^-]*+)*+-----END {KEY}|(?:(?:\s|\\n)*+[A-Za-z0-9+/]{{32,}}+={{0,2}})++)"),
    Rule("aws_key_id", ("akia", "asia", "abia", "acca"), r"(?<![A-Za-z0-9])(?:AKIA|ASIA|ABIA|ACCA)[A-Z0-9]{16}" + END),
    Rule("github_token", ("ghp_", "gho_", "ghu_", "ghs_", "ghr_"), r"(?<![A-Za-z0-9])gh[pousr]_[A-Za-z0-9]{36}" + END, crc_tail),
    Rule("github_fine_token", ("github_pat_",), r"github_pat_[A-Za-z0-9]{22}_[A-Za-z0-9]{59}" + END),
    Rule("npm_token", ("npm_",), r"(?<![A-Za-z0-9])npm_[A-Za-z0-9]{36}" + END, crc_tail),
    Rule("slack_token", ("xoxb-", "xoxa-", "xoxp-", "xoxr-", "xoxs-"), r"xox[abprs]-[A-Za-z0-9-]{10,250}+"),
    Rule("slack_hook", ("hooks.slack.com/",), r"hooks\.slack\.com/services/[A-Za-z0-9/+]{40,250}+"),
    Rule("stripe_key", ("sk_live_", "rk_live_", "sk_test_", "rk_test_"), r"(?<![A-Za-z0-9])[sr]k_(?:live|test)_[A-Za-z0-9]{16,250}+"),
    Rule("google_key", ("aiza",), r"(?<![A-Za-z0-9])AIza[A-Za-z0-9_-]{35}(?![A-Za-z0-9_-])"),
    Rule("sendgrid_key", ("sg.",), r"(?<![A-Za-z0-9])SG\.[A-Za-z0-9_-]{22}\.[A-Za-z0-9_-]{43}(?![A-Za-z0-9_-])"),
    Rule("gitlab_token", ("glpat-",), r"(?<![A-Za-z0-9])glpat-[A-Za-z0-9_-]{20,64}+(?![A-Za-z0-9_-])"),
    Rule("pypi_token", ("pypi-",), r"(?<![A-Za-z0-9])pypi-[A-Za-z0-9_-]{85,250}+(?![A-Za-z0-9_-])"),
    Rule("hub_token", ("hf_",), r"(?<![A-Za-z0-9])hf_[A-Za-z]{34}" + END),
    Rule("web_token", ("eyj",), r"(?<![A-Za-z0-9_-])eyJ[A-Za-z0-9_-]++\.eyJ[A-Za-z0-9_-]++\.[A-Za-z0-9_-]++", json_header),
    Rule("url_password", ("://",), r"://[^\s/:@]++:(?P<s>[^\s/:@]{3,}+)@[A-Za-z0-9.-]++"),
    Rule("bearer", ("bearer ",), r"(?i:bearer )(?P<s>[A-Za-z0-9+/_.~=-]{20,%d}+)(?![A-Za-z0-9+/_.~=-])" % MAX_VALUE, spread),
    Rule(
        "assigned_value",
        ("token", "secret", "api_key", "apikey", "api-key", "access_key", "private_key", "credential"),
        WORDS + GIVEN + r"(?:[\"'](?P<q>[^\s\"']{%d,%d}+)[\"']|(?P<s>[A-Za-z0-9+/_.~=-]{%d,%d}+)(?![A-Za-z0-9+/_.~=-]))" % (MIN_VALUE, MAX_VALUE, MIN_VALUE, MAX_VALUE),
        spread,
    ),
    # of a password any characters may be part, up to white space, a quote or a closing delimiter
    Rule(
        "assigned_value",
        ("password", "passwd", "pwd"),
        PASSWORDS + GIVEN + r"(?:[\"'](?P<q>[^\s\"']{%d,%d}+)[\"']|(?P<s>[^\s\"',;<>(){}\[\]]{%d,%d}+)(?![^\s\"',;<>(){}\[\]]))" % (MIN_PASSWORD, MAX_VALUE, MIN_PASSWORD, MAX_VALUE),
        spread,
    ),
)


@lru_cache(None)
def scanner() -> tuple[ahocorasick.Automaton, tuple[re.Pattern[str], ...]]:
    by: dict[str, list[int]] = {}
    for i, r in enumerate(RULES):
        for k in r.keywords:
            by.setdefault(k, []).append(i)
    auto = ahocorasick.Automaton()
    for k, rules in by.items():
        auto.add_word(k, (len(k), tuple(rules)))
    auto.make_automaton()
    return auto, tuple(re.compile(r.pattern) for r in RULES)


def matches(text: str, rule: int, pattern: re.Pattern[str], at: int) -> tuple[int, int, int] | None:
    m = pattern.match(text, at)
    if not m:
        return None
    group = next((g for g in ("q", "s") if g in pattern.groupindex and m[g] is not None), 0)
    return (rule, m.start(group), m.end(group)) if RULES[rule].check(m[group]) else None


def resolved(found: set[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """(rule, start, stop) without overlaps, by start."""
    return sorted(disjoint(sorted(found, key=lambda x: (x[0], x[1] - x[2], x[1])), 1, 2), key=lambda x: x[1])


def scan(text: str | None) -> list[tuple[int, int, int]]:
    if not text:
        return []
    auto, patterns = scanner()
    found = set()
    for end, (size, rules) in auto.iter(lowered(text)):
        for r in rules:
            hit = matches(text, r, patterns[r], end - size + 1)
            if hit:
                found.add(hit)
    return resolved(found) if found else []


def redacted(text: str | None) -> str | None:
    """The text with each secret replaced by its rule's name; text itself where it holds none."""
    out, at = [], 0
    for rule, start, stop in scan(text):
        out += [text[at:start], f"[{RULES[rule].name}]"]
        at = stop
    return "".join([*out, text[at:]]) if out else text


def find_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, rule, start, stop, digest), one row a secret; digest is the SHA-256 of the secret, which itself isn't returned."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            out: list[tuple] = []
            for b in chunks(whole, "text"):
                for i, t in zip(b.column("doc_id").to_pylist(), b.column("text").to_pylist()):
                    out += [(i, RULES[r].name, start, stop, hashlib.sha256(t[start:stop].encode("utf-8", "replace")).hexdigest()) for r, start, stop in scan(t)]
            cols = list(zip(*out)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string()))], ["doc_id", "rule", "start", "stop", "digest"])

    src = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return src.mapInArrow(run, "doc_id bigint, rule string, start bigint, stop bigint, digest string")


def redact_documents(docs: DataFrame, text_col: str = "text", size_col: str = "n_chars") -> DataFrame:
    """docs with secrets replaced in the text column, and size_col, where there is one, set to the new length of the texts that changed.
    All other columns and the order of columns stay."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            at = whole.schema.get_field_index(text_col)
            size_at = whole.schema.get_field_index(size_col)
            for b in chunks(whole, text_col):
                cols = list(b.columns)
                old = cols[at].to_pylist()
                new = [redacted(t) for t in old]
                cols[at] = pa.array(new, cols[at].type)
                if size_at >= 0:
                    cols[size_at] = pa.array([n if a is b_ else len(b_) for n, a, b_ in zip(cols[size_at].to_pylist(), old, new)], cols[size_at].type)
                yield pa.RecordBatch.from_arrays(cols, schema=b.schema)

    return docs.mapInArrow(run, docs.schema)
