"""Personal data by candidate gradient boosting.

High-recall generators propose spans that may overlap; boosted trees score each by its format and its context; a threshold for each kind, set on
held-out examples, selects the redactions.

The trees are trained here, on examples that are made from templates with a fixed seed: personal data of each kind in many formats among
look-alikes (version and order numbers, dates, measures, hashes, code).  Nothing is read from the corpus to train, so the model is the same for any data.

Scores are calibrated and thresholds are set on examples of another generator than that of training: prose of four languages around the spans, other lead
words, formats and look-alikes.  An isotonic curve turns the trees' scores into shares of true spans; tests measure it on a third seed.

Definitions for odd input.  Null and empty texts hold nothing.  Offsets are characters of the whole text, which is never cut; `stop` is exclusive.  Of selected spans that overlap, the one of
the higher score stays, then the longer, then the earlier.  Repeated rows repeat their spans.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks, disjoint

KINDS = ("email", "phone", "card", "ip", "iban", "ssn")
GENERATORS = (
    # starts where a run starts, so that a long run is read once
    re.compile(r"(?<![^\s@<>\"'(),;:])[^\s@<>\"'(),;:]++@[^\s@<>\"'(),;:]++"),
    re.compile(r"(?<![\w.])[+(]?\d[\d()./ -]{5,22}\d(?!\w)"),
    re.compile(r"(?<![\w])\d(?:[ -]?\d){11,18}(?![\w])"),
    re.compile(r"(?<![\w.])\d{1,3}\.\d{1,3}\.\d{1,3}\.\d{1,3}(?![\w]|\.\d)"),
    re.compile(r"(?<![\w])[A-Z]{2}\d{2}(?: ?[A-Z0-9]){11,30}(?![\w])"),
    re.compile(r"(?<![\w-])\d{3}[- ]\d{2}[- ]\d{4}(?![\w-])"),
)
#: What a text must hold for any generator to propose anything.
SEED = re.compile(r"@|\d")
HINTS = (("mail", "@", "contact", "write"), ("phone", "call", "tel", "mobile", "fax", "contact"), ("card", "visa", "pay", "credit", "charge"), ("ip", "host", "server", "address", "from", "login"), ("iban", "bank", "account", "transfer"), ("ssn", "social", "security"))
AGAINST = ("version", "order", "isbn", "invoice", "build", "release", "rev", "part", "ratio", "section", "chapter", "page", "http", "sha", "hash", "serial", "v.")
CONTEXT = 32
#: Precision that the threshold of a kind must reach on the examples that calibrate, and the least threshold.
PRECISION = 0.98
LEAST = 0.3
TREES, DEPTH, RATE, EXAMPLES = 80, 3, 0.2, 1200


def luhn(digits: str) -> bool:
    s = [int(c) for c in reversed(digits)]
    return bool(s) and (sum(s[::2]) + sum(sum(divmod(2 * x, 10)) for x in s[1::2])) % 10 == 0


def iban_ok(value: str) -> bool:
    v = value.replace(" ", "")
    return int("".join(str(int(c, 36)) for c in v[4:] + v[:4])) % 97 == 1


def features(kind: int, text: str, start: int, stop: int) -> list[float]:
    s = text[start:stop]
    digits = re.sub(r"\D", "", s)
    before, after = text[max(0, start - CONTEXT) : start].lower(), text[stop : stop + CONTEXT].lower()
    groups = re.findall(r"\d+", s)
    domain = s.rpartition("@")[2].rstrip(".") if "@" in s else ""
    return [
        kind, len(s), len(digits), len(digits) / len(s), len(groups), max(map(len, groups), default=0), min(map(len, groups), default=0),
        s[0] == "+", "(" in s and ")" in s, s.count("-"), s.count(" "), s.count("."), s.count("/"),
        luhn(digits) if len(digits) >= 12 else -1, kind == 4 and iban_ok(s), kind == 3 and all(int(g) < 256 and (g == "0" or g[0] != "0") for g in groups),
        "." in domain and re.fullmatch(r"[A-Za-z]{2,}", domain.rpartition(".")[2]) is not None, domain.count("."), bool(re.fullmatch(r"[\w.%+-]+", s.partition("@")[0])) if domain else -1,
        any(h in before for h in HINTS[kind]), any(h in after for h in HINTS[kind]), any(h in before for h in AGAINST),
        before[-1:] in ("", " ", "\n"), after[:1] in ("", " ", "\n", ".", ",", ";"), before[-1:] in ("=", "#", "/", "-", "_", "$"), after[:1] in ("%", "/", "-", "_", "="),
        int(digits[:4] or 0) if len(digits) in (8, 12, 14) else -1, len(set(digits)), int(digits[0]) if digits else -1, int(groups[0]) if kind in (3, 5) else -1,
        kind == 5 and len(groups) == 3 and ssn_ok(*groups), "." in s.partition("@")[0],
    ]


def ssn_ok(area: str, group: str, serial: str) -> bool:
    """Numbers that are issued: no area 000, 666 or 900 and above, no group 00, no serial 0000."""
    return area not in ("000", "666") and area < "900" and group != "00" and serial != "0000"


def candidates(text: str) -> Iterator[tuple[int, int, int]]:
    """(kind, start, stop); trailing punctuation is not part of a span."""
    if not SEED.search(text):
        return
    for kind, g in enumerate(GENERATORS):
        if kind == 0 and "@" not in text:
            continue
        for m in g.finditer(text):
            stop = m.end()
            while stop > m.start() and text[stop - 1] in ".,;:!?":
                stop -= 1
            if stop - m.start() > 5:
                yield kind, m.start(), stop
            if kind in (1, 2) and " " in m.group():
                # numbers that stand side by side: each alone is proposed too
                for part in re.finditer(r"\+?\d[\d()./-]*(?: ?\(\d+\) ?[\d-]+)?|\(\d+\) ?[\d-]+", m.group()):
                    size = sum(c.isdigit() for c in part.group())
                    if size >= (12 if kind == 2 else 7) and part.end() - part.start() < m.end() - m.start():
                        yield kind, m.start() + part.start(), m.start() + part.end()


class Boosted:
    """Gradient-boosted trees for a yes/no label: logistic loss, Newton leaves, exact splits on quantile cuts."""

    def __init__(self, x: np.ndarray, y: np.ndarray) -> None:
        self.base = float(np.log(max(y.mean(), 1e-6) / max(1 - y.mean(), 1e-6)))
        self.trees: list[list] = []
        cuts = [np.unique(np.quantile(x[:, f], np.linspace(0.02, 0.98, 33))) for f in range(x.shape[1])]
        score = np.full(len(y), self.base)
        for _ in range(TREES):
            p = 1 / (1 + np.exp(-score))
            g, h = y - p, p * (1 - p)
            tree = self.grown(x, g, h, np.arange(len(y)), cuts, DEPTH)
            self.trees.append(tree)
            score += RATE * self.leaf(tree, x)

    def grown(self, x, g, h, rows, cuts, depth) -> list:
        G, H = g[rows].sum(), h[rows].sum()
        best = (1e-6, -1, 0.0)
        if depth:
            for f, cs in enumerate(cuts):
                v = x[rows, f]
                order = np.searchsorted(cs, v, side="left")
                gl, hl = np.cumsum(np.bincount(order, g[rows], len(cs) + 1))[:-1], np.cumsum(np.bincount(order, h[rows], len(cs) + 1))[:-1]
                gain = gl**2 / (hl + 1) + (G - gl) ** 2 / (H - hl + 1) - G**2 / (H + 1)
                gain[(hl < 1) | (H - hl < 1)] = 0
                k = int(gain.argmax())
                if gain[k] > best[0]:
                    best = (gain[k], f, cs[k])
        if best[1] < 0:
            return [-1, G / (H + 1)]
        low = x[rows, best[1]] <= best[2]
        return [best[1], best[2], self.grown(x, g, h, rows[low], cuts, depth - 1), self.grown(x, g, h, rows[~low], cuts, depth - 1)]

    def leaf(self, tree: list, x: np.ndarray) -> np.ndarray:
        if tree[0] < 0:
            return np.full(len(x), tree[1])
        return np.where(x[:, tree[0]] <= tree[1], self.leaf(tree[2], x), self.leaf(tree[3], x))

    def probability(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-(self.base + RATE * sum(self.leaf(t, x) for t in self.trees))))


#: Prose for the examples that calibrate.
PROSE = (
    "the report was sent on monday and we will meet again after lunch to talk about it with the team".split(),
    "der bericht wurde am montag verschickt und wir treffen uns nach dem essen wieder um darüber zu reden".split(),
    "le rapport a été envoyé lundi et nous allons nous revoir après le repas pour en parler avec eux".split(),
    "el informe se envió el lunes y nos veremos otra vez después de comer para hablar de ello".split(),
)
LEADS = (("write to", "my mail:", "Kontakt", "e-mail"), ("call me at", "Tel.", "mobile:", "ring"), ("card", "Visa", "charged to"), ("logged in from", "host", "server at"), ("account", "IBAN", "transfer to"), ("SSN", "social security no."))
AGAINST_LEADS = ("order no.", "version", "ISBN", "invoice", "build", "page", "section", "ticket", "lot", "model")


def others(n: int, seed: int) -> list[tuple[str, list[tuple[int, int, int]]]]:
    """(text, its personal data) by another generator than that of training."""
    r = np.random.default_rng(seed)
    d = lambda k: "".join(map(str, r.integers(0, 10, k)))
    one = lambda k: str(int(r.integers(1, 10))) + d(k - 1)
    pick = lambda *a: a[int(r.integers(len(a)))]
    names = ("anna", "lukas", "maria", "john", "chloe", "diego", "smith", "weber", "dubois", "garcia", "kim", "okafor")
    hosts = ("gmail.com", "x.com", "q.nl", "web.de", "orange.fr", "uni-bonn.de", "example.org", "corp.example.co.uk", "mail.example.net")

    def card() -> str:
        body = pick("4" + d(14), "5" + pick("1", "2", "5") + d(13), "3" + pick("4", "7") + d(12))
        s = next(body + c for c in "0123456789" if luhn(body + c))
        return pick(s, " ".join(s[i : i + 4] for i in range(0, len(s), 4)), "-".join(s[i : i + 4] for i in range(0, len(s), 4)))

    def iban() -> str:
        country, body = pick("DE", "ES", "PL", "IT", "CH"), d(int(r.integers(15, 21)))
        digits = "".join(str(int(c, 36)) for c in body + country + "00")
        return f"{country}{98 - int(digits) % 97:02d}{body}"

    def ssn() -> str:
        area = int(pick(r.integers(1, 666), r.integers(667, 900)))
        return f"{area:03d}-{int(r.integers(1, 100)):02d}-{int(r.integers(1, 10000)):04d}"

    good = (
        lambda: pick(f"{pick(*names)}.{pick(*names)}", f"{pick(*names)}{d(2)}", f"{pick(*names)}_{pick(*names)}", f"{pick(*names)[0]}{pick(*names)}") + "@" + pick(*hosts),
        lambda: pick(f"({one(3)}) {one(3)}-{d(4)}", f"{one(3)}-{one(3)}-{d(4)}", f"+1 {one(3)} {one(3)} {d(4)}", f"+49 {one(3)} {one(7)}", f"+33 {one(1)} {d(2)} {d(2)} {d(2)} {d(2)}", f"+{pick('1', '44', '34')}{one(10)}", f"+1-{one(3)}-{one(3)}-{d(4)}"),
        card, lambda: ".".join(str(int(x)) for x in r.integers(1, 255, 4)), iban, ssn,
    )
    bad = (
        lambda: pick(f"{pick(*names)}@", f"@{pick(*names)}", f"{pick(*names)}@{pick(*names)}", f"{d(2)}@{d(1)}.{d(2)}"),
        lambda: pick(f"19{d(2)}-0{one(1)}-1{d(1)}", f"1{d(1)}.0{one(1)}.20{d(2)}", f"20{d(2)}-20{d(2)}", one(8), one(7), f"{one(1)}.{d(3)}.{d(3)}", f"{one(2)}/{one(2)}/20{d(2)}", f"978{d(10)}"),
        lambda: next(x for x in iter(lambda: one(16), "") if not luhn(x)),
        lambda: pick(f"{int(r.integers(256, 999))}.{d(1)}.{d(1)}.{d(2)}", f"{one(1)}.{d(1)}.{d(1)}.{d(1)}"),
        lambda: next(x for x in iter(lambda: f"{pick('QX', 'ZZ', 'DE')}{d(2)}{d(17)}", "") if not iban_ok(x)),
        lambda: pick(f"000-{d(2)}-{d(4)}", f"9{d(2)}-{d(2)}-{d(4)}", f"666-{d(2)}-{d(4)}", f"{one(3)}-00-{d(4)}"),
    )
    out = []
    for _ in range(n):
        prose = PROSE[int(r.integers(len(PROSE)))]
        fill = lambda: " ".join(r.choice(prose, int(r.integers(1, 9))))  # noqa: B023, E731
        text, held = fill(), []
        for _ in range(int(r.integers(1, 4))):
            kind, yes = int(r.integers(len(KINDS))), r.random() < 0.5
            lead = pick("", "", *(LEADS[kind] if yes or r.random() < 0.25 else AGAINST_LEADS))
            text += f" {lead} " if lead else " "
            s = (good if yes else bad)[kind]()
            if yes:
                held.append((kind, len(text), len(text) + len(s)))
            text += s + pick(" ", "\n", ", ", ". ") + fill()
        out.append((text, held))
    return out


def examples(n: int, seed: int) -> list[tuple[str, list[tuple[int, int, int]]]]:
    """(text, its personal data as (kind, start, stop)) from templates; for training."""
    r = np.random.default_rng(seed)
    d = lambda k: "".join(map(str, r.integers(0, 10, k)))
    pick = lambda *a: a[int(r.integers(len(a)))]
    letters = "abcdefghijklmnopqrstuvwxyz"
    word = lambda: "".join(r.choice(list(letters), int(r.integers(2, 9))))

    def valid_card() -> str:
        body = pick("4", "51", "53", "55", "37", "6011", "62") + d(14)
        body = body[: pick(15, 15, 15, 14)]
        return next(body + c for c in "0123456789" if luhn(body + c))

    def spaced(s: str) -> str:
        gap = pick("", "", " ", "-")
        return gap.join(s[i : i + 4] for i in range(0, len(s), 4))

    def iban() -> str:
        country, body = pick("DE", "FR", "ES", "GB", "NL"), d(int(r.integers(12, 24)))
        check = 98 - int("".join(str(int(c, 36)) for c in body + country + "00")) % 97
        s = f"{country}{check:02d}{body}"
        return pick(s, " ".join(s[i : i + 4] for i in range(0, len(s), 4)))

    octet = lambda: str(int(r.integers(1, 255)))
    good = (
        lambda: pick(f"{word()}.{word()}", f"{word()}{d(2)}", f"{word()}.{d(2)}", f"{word()}_{word()}") + "@" + pick(f"{word()}.com", f"{word()}{d(1)}.example.com", f"{word()}.{word()}.org", f"mail.{word()}.de", f"{word()[0]}.{pick('fr', 'io', 'org')}"),
        lambda: pick(f"+1 ({d(3)}) {d(3)}-{d(4)}", f"({d(3)}) {d(3)}-{d(4)}", f"{d(3)}-{d(3)}-{d(4)}", f"+{pick('44', '49', '33', '34')} {d(2)} {d(4)} {d(4)}", f"+1-{d(3)}-{d(3)}-{d(4)}", f"+{pick('1', '49', '33')}{d(10)}"),
        lambda: spaced(valid_card()),
        lambda: ".".join(octet() for _ in range(4)),
        iban,
        lambda: next(x for x in iter(lambda: f"{d(3)}-{d(2)}-{d(4)}", "") if ssn_ok(*x.split("-"))),
    )
    bad = (
        lambda: pick(f"@{word()}", f"{word()}@{word()}", f"{word()}@{d(2)}", f"git@{word()}", f"x@{d(1)}.{d(1)}"),
        lambda: pick(f"{d(4)}-{d(2)}-{d(2)}", f"{d(2)}/{d(2)}/{d(4)}", f"{d(4)} - {d(4)}", f"{d(3)}.{d(4)}", f"{d(8)}", f"{d(7)}", f"{d(10)}", f"{d(2)}.{d(2)}.{d(4)}", f"{d(3)} {d(3)} {d(3)}", f"{d(13)}"),
        lambda: next(x for x in iter(lambda: pick("", "1", "9", "8") + d(16), 0) if not luhn(x)),
        lambda: pick(f"{int(r.integers(256, 999))}.{d(1)}.{d(2)}.{d(3)}", f"0{d(2)}.0{d(1)}.{d(3)}.{d(1)}", f"{d(1)}.{d(1)}.{d(1)}.{d(1)}"),
        lambda: next(x for x in iter(lambda: f"{pick('AB', 'XY', 'DE', 'GB')}{d(2)}{d(int(r.integers(12, 24)))}", "") if not iban_ok(x)),
        lambda: pick(f"000-{d(2)}-{d(4)}", f"9{d(2)}-{d(2)}-{d(4)}", f"666-{d(2)}-{d(4)}", f"1{d(2)}-00-{d(4)}", f"2{d(2)}-{d(2)}-0000"),
    )
    fill = lambda: " ".join(word() for _ in range(int(r.integers(1, 6))))
    out = []
    for _ in range(n):
        text, held = fill(), []
        for _ in range(int(r.integers(1, 4))):
            kind, yes = int(r.integers(len(KINDS))), r.random() < 0.55
            lead = pick("", "", "", *(HINTS[kind] if yes or r.random() < 0.4 else AGAINST))
            text += " " + (lead + pick(" ", ": ", " is ") if lead and lead != "@" else "")
            s = (good if yes else bad)[kind]()
            if yes:
                held.append((kind, len(text), len(text) + len(s)))
            text += s + pick(" ", " ", "\n", ", ", ". ") + fill()
        out.append((text, held))
    return out


def labelled(texts: list[tuple[str, list[tuple[int, int, int]]]]) -> tuple[np.ndarray, np.ndarray]:
    x, y = [], []
    for t, held in texts:
        truth = set(held)
        for c in candidates(t):
            x.append(features(c[0], t, c[1], c[2]))
            y.append(c in truth)
    return np.array(x, np.float64), np.array(y, np.float64)


class Model:
    """Trees, the isotonic curve of their scores, and the threshold of each kind on calibrated scores."""

    def __init__(self, trees: Boosted, x: np.ndarray, y: np.ndarray) -> None:
        self.trees = trees
        raw = trees.probability(x)
        order = np.argsort(raw, kind="stable")
        self.knots, self.shares = isotonic(raw[order], y[order])
        self.limits = np.full(len(KINDS), 0.5)
        p = self.probability(x)
        for k in range(len(KINDS)):
            on = x[:, 0] == k
            for limit in np.unique(p[on]):  # the lowest at which precision is reached
                if y[on][p[on] >= limit].mean() >= PRECISION:
                    self.limits[k] = max(limit, LEAST)
                    break

    def probability(self, x: np.ndarray) -> np.ndarray:
        return np.interp(self.trees.probability(x), self.knots, self.shares)


def isotonic(score: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(mean score, share) of the blocks of the rising curve that fits best, by pooling neighbours; scores rise."""
    blocks: list[list[float]] = []  # sum of scores, sum of y, rows
    for a, b in zip(score.tolist(), y.tolist()):
        blocks.append([a, b, 1.0])
        while len(blocks) > 1 and blocks[-2][1] * blocks[-1][2] >= blocks[-1][1] * blocks[-2][2]:
            last = blocks.pop()
            blocks[-1] = [u + v for u, v in zip(blocks[-1], last)]
    return np.array([b[0] / b[2] for b in blocks]), np.array([b[1] / b[2] for b in blocks])


@lru_cache(1)
def model() -> Model:
    return Model(Boosted(*labelled(examples(EXAMPLES, 1))), *labelled(others(EXAMPLES, 2)))


def selected(found: list[tuple[int, int, int, float]]) -> list[tuple[int, int, int, float]]:
    order = sorted(found, key=lambda c: (-round(c[3], 6), c[1] - c[2], c[1], c[0]))
    return sorted(disjoint(order, 1, 2), key=lambda c: c[1])


def scan(texts: list[str | None], m: Model) -> list[list[tuple[int, int, int, float]]]:
    """For each text its (kind, start, stop, score)."""
    spans, x = [], []
    for i, t in enumerate(texts):
        if t:
            for c in candidates(t):
                spans.append((i, *c))
                x.append(features(c[0], t, c[1], c[2]))
    out: list[list[tuple[int, int, int, float]]] = [[] for _ in texts]
    if spans:
        for (i, k, a, b), p in zip(spans, m.probability(np.array(x, np.float64)).tolist()):
            if p >= m.limits[k]:
                out[i].append((k, a, b, p))
    return [selected(o) if len(o) > 1 else o for o in out]


def redacted(text: str | None) -> str | None:
    """The text with each selected span replaced by its kind."""
    out, at = [], 0
    for k, a, b, _ in scan([text], model())[0]:
        out += [text[at:a], f"[{KINDS[k]}]"]
        at = b
    return "".join([*out, text[at:]]) if out else text


def find_personal(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, kind, start, stop, score), one row a selected span."""
    held = docs.sparkSession.sparkContext.broadcast(model())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = held.value
        for whole in batches:
            out: list[tuple] = []
            for b in chunks(whole, "text"):
                ids = b.column("doc_id").to_pylist()
                for i, spans in zip(ids, scan(b.column("text").to_pylist(), m)):
                    out += [(i, KINDS[k], a, z, round(p, 6)) for k, a, z, p in spans]
            cols = list(zip(*out)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.float64()))], ["doc_id", "kind", "start", "stop", "score"])

    src = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return src.mapInArrow(run, "doc_id bigint, kind string, start bigint, stop bigint, score double")
