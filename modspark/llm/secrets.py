"""Secret scan with corpus-wide ownership frequency.

Each text is scanned once for candidate credentials. The hashes of the candidates' values are then counted over the whole
corpus, by distinct repositories (texts of an owner) and distinct owners. A value that many owners hold is a copied example;
one that a single owner holds, in however many repositories, and with the entropy of a random key, looks live. All other
candidates are unsure, and are told as such. Each place in a text holds one candidate: a long token beside or around the value
of a pattern adds nothing to it.

Defined results: a null text scans as an empty one; a null owner is an owner of its own (the unnamed one); equal texts of
one owner count as one repository (told apart by 64 bits of hash, so a count can be too low by a collision, about one in 10^9
values held by 10^5 texts); repeated rows are told each for itself; an empty table gives an empty result; a column of the input that
isn't asked for is never read, so clashing names do no harm. Nothing is capped: a value in a third of all rows is pre-aggregated per task.
"""

from __future__ import annotations

import hashlib
import math
import re
from bisect import bisect_left, bisect_right
from collections import Counter

import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: The patterns of the contract.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex")
#: What the ownership makes of a candidate; these kinds follow the patterns' kinds.
LABELS = ("live", "example", "unsure")
#: A long unbroken token that may be a key though no pattern names its form.
OPAQUE = re.compile(r"[A-Za-z0-9+/_=-]{20,}")
MIN_ASSIGN, MIN_ACCESS = 6, 20

SCAN_SCHEMA = (
    "n_assign long, n_access long, n_hex long, base_sha256 string, "
    "base array<struct<start:int,kind:int,end:int>>, candidates array<struct<h:string,start:int,end:int,entropy:double>>"
)


def entropy(value: str) -> float:
    """Shannon entropy of the characters, in bits."""
    n = len(value)
    return -sum(c / n * math.log2(c / n) for c in Counter(value).values()) if n else 0.0


def base_spans(text: str) -> list[tuple[int, int, int, int, int]]:
    """(start, kind, end, value start, value end) of every contract match."""
    out = []
    for m in ASSIGN.finditer(text):
        if m.end(2) - m.start(2) >= MIN_ASSIGN:
            out.append((m.start(), 0, m.end(), m.start(2), m.end(2)))
    for m in ACCESS.finditer(text):
        if m.end() - m.start() >= MIN_ACCESS:
            out.append((m.start(), 1, m.end(), m.start(), m.end()))
    for m in HEX.finditer(text):
        out.append((m.start(), 2, m.end(), m.start(), m.end()))
    out.sort()
    return out


def opaque_spans(text: str) -> list[tuple[int, int]]:
    """Long tokens with letters and digits."""
    return [m.span() for m in OPAQUE.finditer(text) if re.search("[0-9]", m[0]) and re.search("[A-Za-z]", m[0])]


def joined(spans) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e, *_ in spans)


def values_of(text: str, found: list[tuple]) -> list[tuple[int, int]]:
    """(start, end) of the candidates, in order: the patterns' values (the longest of those that overlap), then tokens that touch none."""
    out: list[tuple[int, int]] = []
    for a, b in sorted({(a, b) for *_, a, b in found}, key=lambda x: (x[0], -x[1])):
        if not out or a >= out[-1][1]:
            out.append((a, b))
    starts, ends = [a for a, _ in out], [b for _, b in out]
    free = [(a, b) for a, b in opaque_spans(text) if bisect_right(ends, a) == bisect_left(starts, b)]
    return sorted(out + free)


def scan_text(text: str) -> tuple:
    found = base_spans(text)
    counts = [0, 0, 0]
    for x in found:
        counts[x[1]] += 1
    base = [{"start": s, "kind": k, "end": e} for s, k, e, *_ in found]
    cands = [{"h": xxhash.xxh3_128_hexdigest(text[a:b].encode("utf-8", "surrogatepass")), "start": a, "end": b, "entropy": entropy(text[a:b])} for a, b in values_of(text, found)]
    return (*counts, hashlib.sha256(joined(found).encode()).hexdigest(), base, cands)


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", owner_col: str = "source") -> DataFrame:
    """One row per input row: base spans and candidates, without the text. row: a number of its own, once the table is written."""
    @F.pandas_udf(SCAN_SCHEMA)
    def found(texts: pd.Series) -> pd.DataFrame:
        return pd.DataFrame([scan_text(t) for t in texts], columns=["n_assign", "n_access", "n_hex", "base_sha256", "base", "candidates"])

    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(owner_col).cast("string").alias("owner"), common.whole_text(docs, text_col).alias("text"))
    return src.select("doc_id", "owner", F.monotonically_increasing_id().alias("row"), F.xxhash64("text").alias("text_key"), found("text").alias("found")).select("doc_id", "owner", "row", "text_key", "found.*")


def ownership(scanned: DataFrame) -> DataFrame:
    """h, n_repos, n_owners over all rows. Sums with map-side combining: a hot value is one row per task and text, then one per task."""
    each = scanned.select("owner", "text_key", F.explode(F.array_distinct(F.transform("candidates", lambda c: c["h"]))).alias("h")).groupBy("h", "owner", "text_key").agg(F.count("*").alias("rows"))
    return each.groupBy("h", "owner").agg(F.count("*").alias("n")).groupBy("h").agg(F.sum("n").alias("n_repos"), F.count("*").alias("n_owners"))


def detect(docs: DataFrame, max_owners: int = 1, min_example_owners: int = 3, min_entropy: float = 2.8, **columns) -> DataFrame:
    """Per input row: base counts, and all spans in order: the patterns', and those of live-looking values, of copied examples and of all
    other candidates; most_repos: the greatest number of repositories that one of the row's values is in.

    max_owners: a live value is held by at most so many owners.
    min_example_owners: from so many owners on, a value is an example. min_entropy: bits per character of a live value.
    """
    scanned = common.keep(scan(docs, **columns), "secrets")
    freq = ownership(scanned)
    each = scanned.select("row", F.explode("candidates").alias("c")).select("row", "c.*")
    first = len(KINDS)
    label = (
        F.when(F.col("n_owners") >= min_example_owners, first + 1)
        .when((F.col("n_owners") <= max_owners) & (F.col("entropy") >= min_entropy), first)
        .otherwise(first + 2)
    )
    told = each.join(freq, "h").withColumn("kind", label)
    per_row = told.groupBy("row").agg(F.collect_list(F.struct("start", "kind", "end")).alias("found"), F.max("n_repos").alias("n_repos"))
    out = scanned.join(per_row, "row", "left")
    every = F.array_sort(F.concat("base", F.coalesce("found", F.expr("cast(array() as array<struct<start:int,kind:int,end:int>>)"))))
    names = F.array(*[F.lit(x) for x in KINDS + LABELS])
    said = F.array_join(F.transform(every, lambda x: F.concat_ws(":", F.get(names, x["kind"]), x["start"], x["end"])), ",")
    n = lambda kind: F.coalesce(F.when(F.col("found").isNotNull(), F.size(F.filter("found", lambda x: x["kind"] == kind))), F.lit(0)).cast("long")
    return out.select(
        "doc_id", "n_assign", "n_access", "n_hex", "base_sha256", said.alias("spans"),
        n(first).alias("n_live"), n(first + 1).alias("n_example"), n(first + 2).alias("n_unsure"), F.coalesce("n_repos", F.lit(0)).alias("most_repos"),
    )


def op1_secret_ownership(spark: SparkSession, sf_dir: str) -> DataFrame:
    return detect(common.documents(spark, sf_dir))
