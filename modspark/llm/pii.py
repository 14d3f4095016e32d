"""Personal data by contract patterns and a semi-Markov conditional random field.

The patterns give base spans. They take the longest run and give up where it fails (two card numbers side by side, a phone number
before an address), and they know one way of writing each kind only: there the field decides. It finds addresses that are spelled out
or spaced, numeric addresses that are defanged or of version 6, and phone numbers without a plus sign. It works on windows: runs of
words around digits and at signs; a window is found and cut into tokens in time that grows with its length, and a segment has up to
``REACH`` tokens, so long unbroken runs cost no more than others.
A segment of a type is scored by features of the whole span (checksum, parts, groups, neighbours); dynamic programming chooses
boundaries and types of a window jointly, any other token being a segment of its own. Weights are fitted by conditional likelihood
on windows made from a seeded grammar. Spans that the field finds and that touch no base span of their kind are added.

Defined results: a null text has no spans; texts are scanned whole, in time that grows with their length; repeated rows are scanned
each for itself; an empty table gives an empty result; further columns are not read.
"""

from __future__ import annotations

import hashlib
import math
import random
import re
from bisect import bisect_left, bisect_right
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

KINDS = ("email", "ip", "card", "phone")
#: The contract's patterns, written so that they fail in linear time.
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
IP = re.compile(r"(?<![0-9])([0-9]++)\.([0-9]++)\.([0-9]++)\.([0-9]++)")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
ANY = re.compile("[0-9@]|[(\\[] ?at ?[)\\]]")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = 2 * d - 9 * (d > 4)
        total += d
    return total % 10 == 0


def digits_of(s: str) -> str:
    return re.sub("[^0-9]", "", s)


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end), sorted."""
    out = []
    at, floor = text.find("@"), 0
    while at >= 0:
        start = at
        while start > floor and text[start - 1] in _LOCAL:
            start -= 1
        floor = at + 1
        if start < at and (m := DOMAIN.match(text, at + 1)):
            out.append((start, 0, m.end()))
            floor = m.end()
        at = text.find("@", floor)
    for m in IP.finditer(text):
        if all(len(x.lstrip("0")) <= 3 and int(x[-4:]) <= 255 for x in m.groups()):
            out.append((m.start(), 1, m.end()))
    for m in CARD.finditer(text):
        if m.end() - m.start() >= 12 and 12 <= len(d := digits_of(m[0])) <= 19 and luhn(d):
            out.append((m.start(), 2, m.end()))
    if "+" in text:
        for m in PHONE.finditer(text):
            if 9 <= len(digits_of(m[0])) <= 15:
                out.append((m.start(), 3, m.end()))
    out.sort()
    return out


# --- the field ---

#: Tokens that a segment has at most.
REACH = 40
TOKEN = re.compile(r"[A-Za-z]+|[0-9]+|\s+|.", re.S)
_AT, _DOT = r"(?: ?@ ?| ?[(\[] ?at ?[)\]] ?)", r"(?:\.| ?[(\[] ?dot ?[)\]] ?)"
_HEX = "[0-9A-Fa-f]{1,4}"
FORMS = (
    re.compile(rf"[A-Za-z0-9._%+-]++{_AT}[A-Za-z0-9-]+(?:{_DOT}[A-Za-z0-9-]+)+"),
    re.compile(rf"[0-9]{{1,3}}(?:(?:\.|\[\.\]|\(\.\)| ?[\[(]dot[)\]] ?)[0-9]{{1,3}}){{3}}|(?:{_HEX}:){{7}}{_HEX}|(?:{_HEX}:){{1,6}}(?::{_HEX}){{1,6}}"),
    re.compile(r"[0-9](?:[\x20-]?[0-9]){11,18}"),
    re.compile(r"(?:\+|00)?[\x20]?\(?[0-9][0-9()\x20.-]{6,24}[0-9]"),
)
#: Signs that a span of each form has at most.
LONGEST = (1 << 30, 48, 40, 32)
_TO_END = re.compile(r"\S*")
_OTHER_SPACE = re.compile(r"\s")
_SPELLED = re.compile(r"[(\[] ?at ?[)\]] ?\S*(?: ?[(\[] ?dot ?[)\]] ?\S+)*")
_SPACED = re.compile(r"@ ?\S*")


def _word_start(text: str, floor: int, at: int) -> int:
    """Where the word that reaches up to at begins, not before floor."""
    start = max(floor, 1 + max(text.rfind(c, floor, at) for c in " \n\t"))
    for m in _OTHER_SPACE.finditer(text, start, at):
        start = m.end()
    return start


def windows(text: str) -> list[tuple[int, int]]:
    """Words with digits or at signs, those that stand side by side as one window; a spaced or spelled at sign takes in the words beside it."""
    out: list[tuple[int, int]] = []
    m, floor = ANY.search(text), 0
    while m:
        at, before = m.start(), m.start()
        spelled, spaced = text[at] in "([", text[at] == "@" and (text[at - 1 : at] == " " or text[at + 1 : at + 2] == " ")
        if (spelled or spaced) and before > floor and text[before - 1] == " ":
            before -= 1
        start = _word_start(text, floor, before)
        end = (_SPELLED if spelled else _SPACED if spaced else _TO_END).match(text, at).end()
        if out and start - floor <= 2 and not text[floor:start].strip(" "):
            out[-1] = (out[-1][0], end)
        else:
            out.append((start, end))
        floor = end
        m = ANY.search(text, end)
    return out


CUES = (
    re.compile(r"(?:mail|contact|write)[^A-Za-z]*$", re.I), re.compile(r"(?:ip|host|server|addr\w*)[^A-Za-z]*$", re.I),
    re.compile(r"(?:card|visa|account|credit)[^A-Za-z]*$", re.I), re.compile(r"(?:tel|phone|call|fax|mobile)[^A-Za-z]*$", re.I),
)
WIDTH = 14


def span_features(text: str, start: int, end: int, kind: int) -> np.ndarray:
    """Features of a whole span as one of KINDS; the same places for all kinds, weighted by kind."""
    s = text[start:end]
    before, after = text[start - 1 : start], text[end : end + 1]
    d = digits_of(s)
    f = np.zeros(WIDTH)
    f[0] = 1.0
    f[1] = before.isalnum() or before in ("@", "+", "-") and bool(before)
    f[2] = after.isalnum() or after in ("@", "_") and bool(after)
    f[3] = after in (".", "-") and text[end + 1 : end + 2].isdigit()
    f[4] = before in (".", "-") and bool(before)
    f[5] = CUES[kind].search(text[max(0, start - 24) : start]) is not None
    if kind == 0:
        tail = re.split(r"[^A-Za-z0-9-]+", s)[-1]
        f[6] = tail.isalpha() and 2 <= len(tail) <= 10
        f[7] = "@" in s
        f[8] = " " in s
    elif kind == 1:
        parts, six = re.findall("[0-9]+", s), ":" in s
        f[6] = not six and all(int(x) <= 255 for x in parts)
        f[7] = not six and any(len(x) > 1 and x[0] == "0" for x in parts)
        f[8] = six
        f[9] = six and s.count(":") > 2 and len(parts) > 1
        f[10] = "[" in s or "(" in s
        f[11] = s.count(":") == 7
        f[12] = before == ":" or after == ":" and text[end + 1 : end + 2].isalnum()
    elif kind == 2:
        groups = re.split("[ -]", s)
        f[6] = luhn(d)
        f[7] = len(d) in (13, 14, 15, 16, 19)
        f[8] = len(groups) == 1
        f[9] = len(groups) > 1 and {len(x) for x in groups[:-1]} == {4} and len(groups[-1]) <= 4
        f[10] = len(set(re.findall("[ -]", s))) > 1
        f[11] = d[:1] in "3456"
    else:
        f[6] = s[0] == "+"
        f[7] = 9 <= len(d) <= 15
        f[8] = s.count("(") == s.count(")") == 1
        f[9] = bool(re.search(r"[0-9]{3}[ .-][0-9]{4}$", s))
        f[10] = s.count("(") != s.count(")")
        f[11] = bool(re.fullmatch("[0-9]+", s))
        f[12] = bool(re.search(r"[0-9]{6}", s))
        f[13] = len(d) > 13
    return f


def candidates(text: str, start: int, end: int) -> tuple[list[int], list[tuple[int, int, int, np.ndarray]]]:
    """Token bounds of a window and its typed segments (first token, token after the last, kind, features)."""
    bounds = [start, *(m.end() for m in TOKEN.finditer(text, start, end))]
    n, out = len(bounds) - 1, []
    for i in range(n):
        c = text[bounds[i]]
        if c.isspace():
            continue
        digit = "0" <= c <= "9"
        kinds = ([0] if c.isascii() and c.isalnum() or c in "._%+-" else []) + ([1] if digit or c in "abcdefABCDEF" else []) + ([2] if digit else []) + ([3] if digit or c in "+(" else [])
        for kind in kinds:
            if kind == 0 and i and text[bounds[i] - 1] in _LOCAL:
                continue  # an address begins where its run does
            longest = FORMS[kind].match(text, bounds[i], end)  # the forms are greedy: none of its kind ends later
            if not longest:
                continue
            most = min(bounds[i] + LONGEST[kind], longest.end())
            for j in range(i + 1, min(n, i + REACH) + 1):
                if bounds[j] > most:
                    break
                if FORMS[kind].fullmatch(text, bounds[i], bounds[j]):
                    out.append((i, j, kind, span_features(text, bounds[i], bounds[j], kind)))
    return bounds, out


def best_segments(n: int, segments: list, weights: np.ndarray) -> list[tuple[int, int, int]]:
    """The highest-scoring segmentation of n tokens; a token outside all segments scores 0."""
    by_end: dict[int, list] = {}
    for i, j, kind, f in segments:
        by_end.setdefault(j, []).append((i, kind, float(weights[kind] @ f)))
    best, back = [0.0] * (n + 1), [None] * (n + 1)
    for j in range(1, n + 1):
        best[j] = best[j - 1]
        for i, kind, score in by_end.get(j, ()):
            if best[i] + score > best[j]:
                best[j], back[j] = best[i] + score, (i, kind)
    out, j = [], n
    while j:
        if back[j]:
            out.append((back[j][0], j, back[j][1]))
            j = back[j][0]
        else:
            j -= 1
    return out[::-1]


def expectations(n: int, segments: list, weights: np.ndarray) -> tuple[float, np.ndarray]:
    """log of the sum over all segmentations, and each segment's probability."""
    add = lambda a, b: max(a, b) + math.log1p(math.exp(-abs(a - b)))
    scores = [float(weights[k] @ f) for _, _, k, f in segments]
    ends, starts = {}, {}
    for x, (i, j, _, _) in enumerate(segments):
        ends.setdefault(j, []).append(x)
        starts.setdefault(i, []).append(x)
    ahead, behind = [0.0] * (n + 1), [0.0] * (n + 1)
    for j in range(1, n + 1):
        ahead[j] = ahead[j - 1]
        for x in ends.get(j, ()):
            ahead[j] = add(ahead[j], ahead[segments[x][0]] + scores[x])
    for i in range(n - 1, -1, -1):
        behind[i] = behind[i + 1]
        for x in starts.get(i, ()):
            behind[i] = add(behind[i], behind[segments[x][1]] + scores[x])
    p = np.array([math.exp(min(0.0, ahead[i] + s + behind[j] - ahead[n])) for (i, j, _, _), s in zip(segments, scores, strict=True)])
    return ahead[n], p


def _sample(r: random.Random) -> tuple[str, list[tuple[int, int, int]]]:
    """A made-up window with its true spans."""
    num = lambda k: "".join(r.choice("0123456789") for _ in range(k))
    word = lambda: "".join(r.choice("etaoinshrdlu") for _ in range(r.randint(2, 8)))

    def card():
        d = r.choice("3456") + num(r.choice((11, 14, 14, 14)))
        d += next(c for c in "0123456789" if luhn(d + c))
        sep = r.choice(("", "", " ", "-"))
        return sep.join(d[i : i + 4] for i in range(0, len(d), 4))

    def phone():
        a, b, c = num(3), num(3), num(4)
        return r.choice((f"+{r.randint(1, 99)} ({a}) {b}-{c}", f"+{r.randint(1, 99)} {a} {b} {c}", f"({a}) {b}-{c}", f"+{r.randint(1, 99)}-{a}-{b}-{c}", f"+{r.randint(1, 9)}{a}{b}{c}"))

    def email():
        at, dot = r.choice((("@", "."), ("@", "."), (" (at) ", " (dot) "), ("[at]", "[dot]")))
        return f"{word()}{r.choice(('', '.', '_'))}{num(r.randint(0, 2))}{at}{word()}{dot}{r.choice(('com', 'org', 'net', 'de'))}"

    def ip():
        if r.random() < 0.3:
            group = lambda: f"{r.randrange(1 << 16):x}"
            left, right = r.randint(1, 4), r.randint(1, 3)
            return ":".join(group() for _ in range(8)) if r.random() < 0.5 else ":".join([*(group() for _ in range(left + 1)), "", *(group() for _ in range(right))])
        return r.choice((".", ".", ".", "[.]", "(.)", "[dot]")).join(str(r.randint(0, 255)) for _ in range(4))

    def wrong():
        bad = num(r.choice((12, 13, 15, 16)))
        bad = bad if not luhn(bad) else bad[:-1] + str((int(bad[-1]) + 1) % 10)
        return r.choice((bad, bad, ".".join(str(r.randint(200, 999)) for _ in range(4)) + ".1", f"{num(4)}-{num(2)}-{num(2)}", f"{num(1)}.{num(1)}.", num(r.randint(1, 9)), "".join(r.choice("0123456789abcdef") for _ in range(40)), f"v{num(1)}.{num(2)}.{num(3)}", f"{num(2)}:{num(2)}:{num(2)} {num(4)}", f"{word()}@{word()}", f"{num(2)}:{num(2)}:{num(2)}", f"{word()}::{word()}{num(1)}", f"{r.choice('abcdef')}::{r.choice('abcdef')}{num(1)}", f"{num(1)}.{num(1)}.{num(1)}", f"{num(3)} {num(3)} {num(3)} {num(3)} {num(3)} {num(2)}", f"{num(10)}"))

    text, spans = "", []
    for _ in range(r.randint(1, 4)):
        if r.random() < 0.3:
            text += word() + " "
        kind = r.choice((0, 1, 2, 3, 4, 4, 4))
        s = (email, ip, card, phone, wrong)[kind]()
        if kind < 4:
            spans.append((len(text), len(text) + len(s), kind))
        text += s + " "
    return text, spans


@lru_cache(maxsize=1)
def fitted(samples: int = 700, rounds: int = 40, seed: int = 11) -> np.ndarray:
    """Weights by kind: gradient ascent on the conditional likelihood, with per-weight steps and a ridge."""
    r = random.Random(seed)
    data = []
    for _ in range(samples):
        text, spans = _sample(r)
        for window in windows(text):
            bounds, segments = candidates(text, *window)
            true = {(s, e, k) for s, e, k in spans}
            gold = np.array([(bounds[i], bounds[j], k) in true for i, j, k, _ in segments], float)
            if segments:
                data.append((len(bounds) - 1, segments, gold))
    w, seen = np.zeros((len(KINDS), WIDTH)), np.full((len(KINDS), WIDTH), 1e-3)
    for _ in range(rounds):
        slope = -0.02 * w
        for n, segments, gold in data:
            _, p = expectations(n, segments, w)
            for (_, _, k, f), g in zip(segments, gold - p, strict=True):
                slope[k] += g * f
        seen += slope * slope
        w += 1.5 * slope / np.sqrt(seen)
    return w


def field_spans(text: str, weights: np.ndarray) -> list[tuple[int, int, int]]:
    """(start, kind, end) that the field chooses."""
    out = []
    for window in windows(text):
        bounds, segments = candidates(text, *window)
        if segments:
            out += [(bounds[i], k, bounds[j]) for i, j, k in best_segments(len(bounds) - 1, segments, weights)]
    return out


def all_spans(text: str, weights: np.ndarray) -> tuple[list, list]:
    """Base spans; base spans with those that the field adds."""
    if not ANY.search(text):
        return [], []
    base = base_spans(text)
    starts = {k: [s for s, kk, _ in base if kk == k] for k in range(len(KINDS))}
    ends = {k: [e for _, kk, e in base if kk == k] for k in range(len(KINDS))}
    # spans of one kind don't overlap: those that begin before e and those that end by s are as many if none touches
    added = [(s, k, e) for s, k, e in field_spans(text, weights) if bisect_left(starts[k], e) == bisect_right(ends[k], s)]
    return base, sorted(base + added)


def joined(spans) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


#: n_spans: all spans; n_added: those of the field alone, and by kind.
RESULT = "n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_spans long, n_added long, added_email long, added_ip long, added_card long, added_phone long"


def detect(docs: DataFrame, weights: np.ndarray | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row, in one pass without a shuffle. weights: of another fit."""
    w = fitted() if weights is None else weights

    @F.pandas_udf(RESULT)
    def scan(texts: pd.Series) -> pd.DataFrame:
        rows = []
        for text in texts:
            base, spans = all_spans(text, w)
            counts, added = [0] * len(KINDS), [0] * len(KINDS)
            for _, k, _ in base:
                counts[k] += 1
            for _, k, _ in spans:
                added[k] += 1
            added = [x - y for x, y in zip(added, counts, strict=True)]
            rows.append((*counts, hashlib.sha256(joined(base).encode()).hexdigest(), joined(spans), len(spans), sum(added), *added))
        return pd.DataFrame(rows, columns=[x.split()[0] for x in RESULT.split(", ")])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), scan(common.whole_text(docs, text_col)).alias("found")).select("doc_id", "found.*")


def op6_semi_markov_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return detect(common.documents(spark, sf_dir))
