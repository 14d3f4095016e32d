"""Context-triggered piecewise fingerprints.

A rolling hash over a few bytes marks where a piece ends, so boundaries move with the content; a second hash of each piece
gives one character of the signature. The block size is the least at which a text has no more than 64 pieces, and a
fingerprint holds the signatures at that block size and at its double. Two fingerprints are compared by edit distance,
where they have a block size in common.

Defined results: null and empty texts have the fingerprint of no bytes, alike with weight 1 to one another; equal texts have
equal fingerprints; texts of any length are read whole; rows with the same id are ordered by their text, a null id goes
with 0; the last row's successor is the first row, also when they are the same row; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common, ordered

#: Pieces that a signature has at most.
MOST = 64
#: log2 of the smallest block size.
LEAST_LEVEL = 2
#: Bytes that the rolling hash covers.
REACH = 7
#: Signatures without a common run of so many characters are unlike.
RUN = 5
ALPHABET = np.frombuffer(b"ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/", dtype=np.uint8)

_ROLL = [np.uint32(pow(0x9E3779B1, k, 1 << 32)) for k in range(REACH)]
_ODD = 0xD1342543DE82EF95
_INVERSE = pow(_ODD, -1, 1 << 64)
_powers: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the piece hash's base and of its inverse modulo 2**64."""
    if len(_powers[0]) < n:
        size = max(n, 2 * len(_powers[0]), 1 << 15)
        for k, base in enumerate((_ODD, _INVERSE)):
            x = np.full(size, base, np.uint64)
            x[0] = 1
            _powers[k] = np.multiply.accumulate(x)
    return _powers[0][:n], _powers[1][:n]


def fingerprint(text: str) -> str:
    """``block:signature:signature at twice the block``."""
    raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
    n = len(raw)
    if not n:
        return f"{1 << LEAST_LEVEL}::"
    wide = raw.astype(np.uint32) + np.uint32(1)
    roll = wide * _ROLL[0]
    for k in range(1, min(REACH, n)):
        roll[k:] += wide[:-k] * _ROLL[k]
    roll ^= roll >> np.uint32(15)
    roll *= np.uint32(0x85EBCA6B)
    roll ^= roll >> np.uint32(13)
    level = LEAST_LEVEL
    while n >> level > 4 * MOST:  # far more boundaries than pieces are expected below
        level += 1
    mask = np.uint32((1 << level) - 1)
    ends = np.flatnonzero((roll & mask) == mask)
    if len(ends) < MOST and level > LEAST_LEVEL:  # fewer than expected, as in repetitive texts: look from the smallest block on
        level = LEAST_LEVEL
        mask = np.uint32((1 << level) - 1)
        ends = np.flatnonzero((roll & mask) == mask)
    while len(ends) >= MOST and level < 31:
        level += 1
        mask = np.uint32((1 << level) - 1)
        ends = ends[(roll[ends] & mask) == mask]
    up, down = _tables(n)
    total = np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * up)
    double = np.uint32((1 << level + 1) - 1)
    return f"{1 << level}:{_signature(total, down, ends, n)}:{_signature(total, down, ends[(roll[ends] & double) == double], n)}"


def _signature(total: np.ndarray, down: np.ndarray, ends: np.ndarray, n: int) -> str:
    stops = ends if len(ends) and ends[-1] == n - 1 else np.append(ends, n - 1)
    sums = total[stops]
    starts = np.concatenate(([0], stops[:-1] + 1))
    sums[1:] -= total[stops[:-1]]
    sums *= down[starts]
    sums ^= sums >> np.uint64(29)
    sums *= np.uint64(0xBF58476D1CE4E5B9)
    return ALPHABET[(sums >> np.uint64(58)).astype(np.int64)].tobytes().decode()


def common_subsequence(a: str, b: str) -> int:
    """Length of the longest common subsequence, a machine word of states at a time."""
    where: dict[str, int] = {}
    for i, c in enumerate(a):
        where[c] = where.get(c, 0) | 1 << i
    full = (1 << len(a)) - 1
    row = full
    for c in b:
        hit = row & where.get(c, 0)
        row = (row + hit | row - hit) & full
    return len(a) - row.bit_count()


def edit_distance(a: str, b: str) -> int:
    """Insertions and deletions that turn a into b."""
    return len(a) + len(b) - 2 * common_subsequence(a, b)


def _alike(a: str, b: str) -> float:
    if a == b:
        return 1.0
    runs = {a[i : i + RUN] for i in range(len(a) - RUN + 1)}
    if not any(b[i : i + RUN] in runs for i in range(len(b) - RUN + 1)):
        return 0.0
    return 1.0 - edit_distance(a, b) / (len(a) + len(b))


def likeness(x: str, y: str) -> float:
    """0 to 1; 1 for equal fingerprints, 0 where no block size is shared."""
    if x == y:
        return 1.0
    (bx, x1, x2), (by, y1, y2) = x.split(":"), y.split(":")
    bx, by = int(bx), int(by)
    if bx == by:
        return max(_alike(x1, y1), _alike(x2, y2))
    if bx == 2 * by:
        return _alike(x1, y2)
    if by == 2 * bx:
        return _alike(x2, y1)
    return 0.0


def fingerprints(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs' columns with ``fingerprint``: one pass, no shuffle."""
    if "fingerprint" in docs.columns:
        docs = docs.drop("fingerprint")
    make = F.pandas_udf(lambda s: s.fillna("").map(fingerprint), "string")
    return docs.withColumn("fingerprint", make(F.col(text_col)))


def edited(text: str, follower: str) -> str:
    """The last quarter replaced by the beginning of the following text."""
    k = len(text) // 4
    return text[: len(text) - k] + follower[:k]


RESULT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
#: edge: 0 a result; 1 the task's first row; 2 its last row, which lacks the row after it.
ROWS = f"{RESULT}, edge int, part int, text string"


def _compared(doc_id, text, mine, follower, next_print):
    other = edited(text, follower)
    theirs = fingerprint(other)
    return (doc_id, len(text), hashlib.sha256(other.encode("utf-8", "surrogatepass")).hexdigest(), mine, theirs, likeness(mine, theirs), likeness(mine, next_print))


def _in_task(batches):
    from pyspark import TaskContext

    part, held = TaskContext.get().partitionId(), None
    blank = (None,) * 6
    for pdf in batches:
        rows = []
        for doc_id, gone, text in zip(pdf["doc_id"], pdf["gone"], pdf["text"], strict=True):
            doc_id = None if gone else int(doc_id)
            mine = fingerprint(text)
            if held is None:
                rows.append((doc_id, *blank, 1, part, text))
            else:
                rows.append((*_compared(*held, text, mine), 0, part, None))
            held = (doc_id, text, mine)
        yield common.frame(rows, ROWS)
    if held is not None:
        yield common.frame([(held[0], *blank, 2, part, held[1])], ROWS)


def _at_ends(batches):
    for pdf in batches:
        rows = []
        for doc_id, gone, text, follower in zip(pdf["doc_id"], pdf["gone"], pdf["text"], pdf["follower"], strict=True):
            rows.append(_compared(None if gone else int(doc_id), text, fingerprint(text), follower, fingerprint(follower)))
        yield common.frame(rows, RESULT)


def against_next(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Each row's fingerprint against that of its edited text and of the row after it in id order."""
    rows = docs.select(*common.id_and_gone(id_col), common.whole_text(docs, text_col).alias("text"))
    done = common.keep(ordered.in_order(rows, "doc_id", "gone", "text").mapInPandas(_in_task, ROWS), "fingerprints")
    firsts, lasts = done.where("edge = 1"), done.where("edge = 2")
    # before: the task whose last row a task's first row follows; the first task's row follows the last row of all
    links = ordered.next_part(firsts.select("part"))
    end = lasts.agg(F.max("part")).first()[0]
    led = firsts.select("part", F.col("text").alias("follower")).join(links, "part").select(F.coalesce("before", F.lit(end)).alias("part"), "follower")
    tail = lasts.select("part", *common.id_and_gone(), "text").join(led, "part").select("doc_id", "gone", "text", "follower").mapInPandas(_at_ends, RESULT)
    return done.where("edge = 0").select(*[x.split()[0] for x in RESULT.split(", ")]).unionByName(tail)


def op3_piecewise_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return against_next(common.documents(spark, sf_dir))
