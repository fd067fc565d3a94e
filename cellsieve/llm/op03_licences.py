"""Licence scans: a generalised suffix automaton of the licence templates' tokens, matching statistics, chains of long matches.

Tokens are lower-cased runs of letters and digits.  The automaton holds every token sequence of every template.  A text is streamed through it
once; after each token the automaton knows the longest ending of the text so far that stands in some template, and by its suffix links the shorter
ones that stand in others.  Of these, each template's matches of at least MIN_MATCH tokens that the next token does not prolong are kept.  Per template, matches in the same order in text and template, with gaps of at most
MAX_GAP tokens between them, form a chain; a chain that covers MIN_COVER of its template is a span.  Of spans that overlap, the one that
covers more tokens stays, then the better cover, then the template that stands first.

Tokens that no template has end every match, so stretches of fewer than MIN_MATCH known tokens are skipped without running the automaton; this
cannot change the outcome.

Definitions for odd input.  Null and empty texts hold nothing.  Offsets are characters of the whole text, `stop` exclusive.  Repeated rows repeat
their spans; a text with one notice several times has a span for each.
"""

from __future__ import annotations

import re
from collections.abc import Iterator, Sequence
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks, disjoint, lowered
from .licence_texts import TEMPLATES

TOKEN = re.compile(r"[^\W_]+")
MIN_MATCH = 3
MAX_GAP = 12
MIN_COVER = 0.8


class SuffixAutomaton:
    """Of several token sequences; places(state) are the (sequence, end) at which the state's sequences end."""

    def __init__(self, sequences: list[list[int]]) -> None:
        self.next: list[dict[int, int]] = [{}]
        self.link, self.length = [-1], [0]
        ends: list[list[tuple[int, int]]] = [[]]
        for s, seq in enumerate(sequences):
            last = 0
            for at, c in enumerate(seq):
                last = self.extend(last, c, ends)
                ends[last].append((s, at + 1))
        self.ends = ends
        self.children: list[list[int]] = [[] for _ in self.link]
        for i, p in enumerate(self.link):
            if p >= 0:
                self.children[p].append(i)
        self.known: dict[int, list[tuple[int, int]]] = {}

    def extend(self, last: int, c: int, ends: list) -> int:
        nxt, link, length = self.next, self.link, self.length
        if c in nxt[last]:
            q = nxt[last][c]
            return q if length[q] == length[last] + 1 else self.split(last, q, c, ends)
        cur = self.state(length[last] + 1, {}, ends)
        p = last
        while p >= 0 and c not in nxt[p]:
            nxt[p][c] = cur
            p = link[p]
        if p < 0:
            link[cur] = 0
        else:
            q = nxt[p][c]
            link[cur] = q if length[q] == length[p] + 1 else self.split(p, q, c, ends)
        return cur

    def split(self, p: int, q: int, c: int, ends: list) -> int:
        clone = self.state(self.length[p] + 1, dict(self.next[q]), ends)
        self.link[clone] = self.link[q]
        self.link[q] = clone
        while p >= 0 and self.next[p].get(c) == q:
            self.next[p][c] = clone
            p = self.link[p]
        return clone

    def state(self, length: int, nxt: dict[int, int], ends: list) -> int:
        self.next.append(nxt)
        self.link.append(0)
        self.length.append(length)
        ends.append([])
        return len(self.link) - 1

    def places(self, state: int) -> list[tuple[int, int]]:
        if state not in self.known:
            out, todo = [], [state]
            while todo:
                i = todo.pop()
                out += self.ends[i]
                todo += self.children[i]
            self.known[state] = sorted(set(out))
        return self.known[state]

    def statistics(self, tokens: list[int]) -> Iterator[tuple[int, int, int]]:
        """(end, length, state) after each token: the longest ending of the tokens so far that stands in a sequence."""
        nxt, link, length = self.next, self.link, self.length
        state = size = 0
        for at, c in enumerate(tokens):
            while state and c not in nxt[state]:
                state = link[state]
                size = length[state]
            if c in nxt[state]:
                state = nxt[state][c]
                size += 1
            else:
                size = 0
            yield at + 1, size, state


class Scanner:
    """The automaton of the templates (name, text), and what a scan needs beside it."""

    def __init__(self, templates: tuple[tuple[str, str], ...]) -> None:
        self.names = [n for n, _ in templates]
        self.ids: dict[str, int] = {}
        seqs = [[self.ids.setdefault(w, len(self.ids)) for w in TOKEN.findall(lowered(t))] for _, t in templates]
        self.automaton, self.lengths = SuffixAutomaton(seqs), [len(s) for s in seqs]


@lru_cache(2)
def scanner(templates: tuple[tuple[str, str], ...] = tuple(TEMPLATES)) -> Scanner:
    return Scanner(templates)


def chained(matches: list[tuple[int, int, int]], length: int) -> Iterator[tuple[int, int, int]]:
    """(text start, text stop, covered template tokens) of disjoint chains of matches (text end, template end, size) of one template, the best first
    among those that overlap."""
    matches = sorted(set(matches))
    best: list[tuple[int, int]] = []  # tokens covered by the best chain that ends here, its text start
    for k, (x, t, n) in enumerate(matches):
        cover, start = n, x - n
        for j in range(k - 1, -1, -1):
            x2, t2, n2 = matches[j]
            if x2 < x - n - MAX_GAP:
                break
            # overlapping ends are cut from the later match
            cut = max(0, x2 - (x - n), t2 - (t - n))
            if cut < n and x2 < x and t2 < t and x - n + cut - x2 <= MAX_GAP and t - n + cut - t2 <= MAX_GAP and best[j][0] + n - cut > cover:
                cover, start = best[j][0] + n - cut, best[j][1]
        best.append((cover, start))
    for cover, start, stop in sorted(((c, s, matches[k][0]) for k, (c, s) in enumerate(best)), key=lambda y: (-y[0], y[2] - y[1], y[1])):
        if cover >= MIN_COVER * length:
            yield start, stop, cover


def spans(tokens: list[int], scan: Scanner) -> list[tuple[int, int, int, int]]:
    """(template, token start, token stop, covered) without overlaps, by start; -1 stands for tokens that no template has."""
    auto, lengths = scan.automaton, scan.lengths
    known = np.array(tokens, np.int64) >= 0
    edge = np.flatnonzero(np.diff(np.concatenate([[0], known.astype(np.int8), [0]])))
    per: dict[int, dict[tuple[int, int], int]] = {}
    for a, b in zip(edge[::2].tolist(), edge[1::2].tolist()):
        if b - a < MIN_MATCH:
            continue
        for end, size, state in auto.statistics(tokens[a:b]):
            # shorter endings, which the suffix links lead to, may stand in further templates
            while size >= MIN_MATCH:
                for s, e in auto.places(state):
                    per.setdefault(s, {}).setdefault((a + end, e), size)
                state = auto.link[state]
                size = auto.length[state]
    found = []
    for s, m in per.items():
        maximal = [(x, e, n) for (x, e), n in m.items() if (x + 1, e + 1) not in m]
        # a template of which all matches together touch too few tokens has no chain
        if touched(maximal) >= MIN_COVER * lengths[s]:
            found += [(s, start, stop, cover) for start, stop, cover in chained(maximal, lengths[s])]
    order = sorted(found, key=lambda f: (-f[3], -f[3] / lengths[f[0]], f[0], f[1], f[2]))
    return sorted(disjoint(order, 1, 2), key=lambda f: f[1])


def touched(matches: list[tuple[int, int, int]]) -> int:
    """Template tokens in any of the matches."""
    out = last = 0
    for start, stop in sorted({(t - n, t) for _, t, n in matches}):
        out += max(0, stop - max(start, last))
        last = max(last, stop)
    return out


def scan(text: str | None, templates: tuple[tuple[str, str], ...] = tuple(TEMPLATES)) -> list[tuple[str, int, int, int, float]]:
    """(licence, start, stop, tokens, cover) of a text."""
    if not text:
        return []
    s = scanner(templates)
    get, low = s.ids.get, lowered(text)
    found = spans([get(w, -1) for w in TOKEN.findall(low)], s)
    if not found:
        return []
    at = [m.span() for m in TOKEN.finditer(low)]
    return [(s.names[k], at[a][0], at[b - 1][1], c, round(c / s.lengths[k], 6)) for k, a, b, c in found]


def find_licences(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", templates: Sequence[tuple[str, str]] = TEMPLATES) -> DataFrame:
    """(doc_id, licence, start, stop, tokens, cover), one row a span: tokens of the template that it covers, and their share of the template.

    templates: (name, text) pairs; a worker builds their automaton once."""
    held = docs.sparkSession.sparkContext.broadcast(tuple((str(n), str(t)) for n, t in templates))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = held.value
        for whole in batches:
            out: list[tuple] = []
            for b in chunks(whole, "text"):
                for i, t in zip(b.column("doc_id").to_pylist(), b.column("text").to_pylist()):
                    out += [(i, *x) for x in scan(t, known)]
            cols = list(zip(*out)) or [()] * 6
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.float64()))], ["doc_id", "licence", "start", "stop", "tokens", "cover"])

    src = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return src.mapInArrow(run, "doc_id bigint, licence string, start bigint, stop bigint, tokens bigint, cover double")
