"""N-gram Jaccard join with adaptive multi-match prefixes.

Texts with equal shingle sets are one node of the link graph. A linked node shares at least t = ceil(3/4 of its size) shingles, so:

1. Shingles are dealt out to buckets and counted by distinct nodes. Those of a single node cannot be shared; a node with more than a
   quarter of such shingles has no link at all, and goes.
2. The others order their shingles, rarest first. Two linked nodes of sizes n and t have at least L shingles in common among their first
   n - t + L, for any L. Each node chooses its L by the estimated cost of its candidates: a longer prefix touches more lists, but
   asks for L matches before a pair is verified.
3. Lists of the prefix shingles give candidates. First a few rounds tie nodes to the fullest node of their lists, so that groups of near
   copies become one component in linear work; then all pairs of nodes of different components that still are candidates are
   verified, so that no link is lost. Pairs within a component need no more work.

Rows between tasks are packed arrays, one row per task and bucket, and no row of pairs is ever made per pair. Hot keys are split. A shingle that
is common within one batch of texts isn't dealt to its bucket by that batch: only its name goes there, so that the bucket knows it for
common, and its owners are sent straight to their nodes, with the greatest frequency there is. What a bucket gets of one shingle is thereby
bounded by the number of batches, not of texts. A prefix list that is too long for one task is cut into blocks, each pair of
blocks a task's work.

Defined results: null texts, and texts without a word, have size 0 and no links; a text of fewer than five words has one shingle, the
whole sequence; texts are read whole; repeated rows are linked as any equal texts; a null id's component is the least id it is linked
with (null if none); an empty table gives an empty result; further columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common
from .components import components

#: Words in a shingle; the threshold as a fraction.
WORDS, OVER, UNDER = 5, 3, 4
#: Rounds that tie nodes to the fullest of their lists before all pairs are listed.
STAR_ROUNDS = 2
#: Matches that a node may ask for, and the costs of a list entry and of a verification in relation.
LEVELS, LIST_COST, VERIFY_COST = (1, 2, 3, 4, 6, 8, 12, 16, 24, 32, 48, 64), 1.0, 40.0
#: Bytes of text for a bucket, and the least and greatest number of buckets (beyond 16 TB of text, buckets grow); up to MOST_TASKS of them,
#: each has a task of its own.
BUCKET_BYTES, LEAST_BUCKETS, MOST_BUCKETS, MOST_TASKS = 16 << 20, 64, 1 << 20, 1 << 16
#: Characters of text that are dealt out at once.
PORTION = 8 << 20
#: Bytes of list entries for a bucket of lists; of nodes' shingles for a bucket of verifications; of pairs that are merged at once: those of a
#: bucket of verifications are in so many shares.
LIST_BYTES, SET_BYTES, PAIR_BYTES, SHARES = 4 << 20, 16 << 20, 8 << 20, 16
#: Shingles that are held as Python sets at once (some 110 bytes each), and from how many on a text's are no set but stay an array.
SET_TOKENS, LONG_SET = 500_000, 50_000
#: A shingle is common in a batch of texts from this share of them on (and HOT_LEAST texts), and from fewer on where a bucket would get more
#: than HOT_ENTRIES of its entries from all batches.
HOT_SHARE, HOT_LEAST, HOT_ENTRIES = 1 / 64, 8, 1 << 19
#: Nodes of a prefix list that one task pairs by itself, and blocks that a longer one is cut into at most; pairs that a task holds.
LIST_NODES, MOST_BLOCKS, HELD_PAIRS = 1024, 64, 1_000_000

_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
_MULT = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F)]


class _WordHashes(dict):
    def __missing__(self, word):
        if len(self) > 200_000:
            self.clear()
        got = self[word] = xxhash.xxh3_64_intdigest(word)
        return got


def _mixed(h: np.ndarray) -> np.ndarray:
    h ^= h >> np.uint64(31)
    h *= np.uint64(0x7FB5D329728EA185)
    h ^= h >> np.uint64(27)
    return h


def shingles(text: str, cache: dict | None = None) -> np.ndarray:
    """The distinct shingles' hashes, sorted."""
    words = text.encode("utf-8", "surrogatepass").translate(_LOWER).split()
    n = len(words)
    if not n:
        return np.empty(0, np.uint64)
    w = np.fromiter(map((_WordHashes() if cache is None else cache).__getitem__, words), np.uint64, n)
    if n < WORDS:
        return np.array([xxhash.xxh3_64_intdigest(w.tobytes(), n)], np.uint64)
    h = w[: n - WORDS + 1] * _MULT[0]
    for k in range(1, WORDS):
        h += _mixed(w[k : n - WORDS + 1 + k] * _MULT[k])
    return np.unique(_mixed(h))


def enough(inter: int, n: int, m: int) -> bool:
    """Whether sets of sizes n and m with so many common members are linked."""
    return UNDER * inter >= OVER * (n + m - inter)


def _pack(*arrays: np.ndarray) -> bytes:
    return np.array([len(a) for a in arrays], "<u4").tobytes() + b"".join(np.ascontiguousarray(a).tobytes() for a in arrays)


def _unpack(data: bytes, *types: str) -> list[np.ndarray]:
    sizes, at, out = np.frombuffer(data, "<u4", len(types)), 4 * len(types), []
    for n, t in zip(sizes.tolist(), types, strict=True):
        out.append(np.frombuffer(data, t, n, at))
        at += n * np.dtype(t).itemsize
    return out


def _gathered(payloads, *types: str) -> list[np.ndarray]:
    got = [_unpack(p, *types) for p in payloads]
    return [np.concatenate([g[k] for g in got]) if got else np.empty(0, t) for k, t in enumerate(types)]


def _runs(keys: np.ndarray) -> np.ndarray:
    """Where runs of equal neighbours begin; the length stands last."""
    if not len(keys):
        return np.zeros(1, np.int64)
    return np.concatenate(([0], np.flatnonzero(keys[1:] != keys[:-1]) + 1, [len(keys)]))


def _short_runs(keys: np.ndarray) -> np.ndarray:
    """As _runs(), with long runs cut, so that a byte holds a run's length."""
    cuts = _runs(keys)
    long = np.flatnonzero(np.diff(cuts) > 255)
    return np.unique(np.concatenate([cuts, *(np.arange(cuts[i], cuts[i + 1], 255) for i in long.tolist())])) if len(long) else cuts


def bucket_of(digests: np.ndarray, buckets: int) -> np.ndarray:
    return ((digests >> np.uint64(40)) % np.uint64(buckets)).astype(np.int64)


# --- 1. shingles by bucket ---

SENT = "bucket int, kind int, payload binary"
#: Kinds of rows: documents; owners of common shingles; names of common shingles; from SOME on, shingles (of bucket kind - SOME once counted).
DOCUMENTS, COMMON, NAMES, SOME = 0, -1, -2, 1


def common_in_batch(each: np.ndarray, least: int) -> np.ndarray:
    """The shingles of which there are at least so many, sorted."""
    slots = (each >> np.uint64(44)).astype(np.int64)
    full = np.bincount(slots, minlength=1 << 20) >= least
    token, n = np.unique(each[full[slots]], return_counts=True)
    return token[n >= least]


def _low(tokens: np.ndarray) -> np.ndarray:
    """The lower 48 bits of each, six bytes apiece."""
    return np.ascontiguousarray(tokens.astype("<u8", copy=False)).view(np.uint8).reshape(-1, 8)[:, :6].reshape(-1)


def _wide(low: np.ndarray) -> np.ndarray:
    wide = np.zeros((len(low) // 6, 8), np.uint8)
    wide[:, :6] = low.reshape(-1, 6)
    return wide.view("<u8").reshape(-1)


def _named(low: np.ndarray, bucket) -> np.ndarray:
    """A shingle's name: its lower 48 bits and its bucket's lower 16."""
    return (low & np.uint64((1 << 48) - 1)) | (np.asarray(bucket).astype(np.uint64) & np.uint64(0xFFFF)) << np.uint64(48)


def _portions(batches, chars: int = PORTION):
    """The batches cut after so many characters of text: what a task holds depends on these, not on the rows of a batch."""
    for pdf in batches:
        ends, at = np.cumsum(pdf["text"].str.len().to_numpy()), 0
        while at < len(pdf):
            to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + chars, "right")))
            yield pdf.iloc[at:to]
            at = to


def _deal(buckets: int, hot: int = 1 << 30):
    """hot: texts from which a shingle is common in a batch of any size."""
    def deal(batches):
        cache = _WordHashes()
        for pdf in _portions(batches):
            sets = [shingles(t, cache) for t in pdf["text"]]
            digests = np.array([xxhash.xxh3_64_intdigest(s.tobytes(), len(s)) for s in sets], np.uint64)
            sizes = np.array([len(s) for s in sets], np.int64)
            rows = []
            ids, gone = pdf["doc_id"].to_numpy().astype(np.int64), pdf["gone"].to_numpy()
            home = bucket_of(digests, buckets)
            for b in np.unique(home).tolist():
                k = np.flatnonzero(home == b)
                rows.append((b, DOCUMENTS, _pack(digests[k], ids[k], gone[k].astype("u1"), sizes[k].astype("<u4"))))
            _, firsts = np.unique(digests, return_index=True)  # equal sets of this batch are sent once
            firsts = firsts[sizes[firsts] > 0]
            if len(firsts):
                each = np.concatenate([sets[i] for i in firsts])
                owner = np.repeat(firsts.astype(np.int32), sizes[firsts])
                place = ((each >> np.uint64(40)) * np.uint64(buckets) >> np.uint64(24)).astype(np.uint16 if buckets <= 1 << 16 else np.uint32)
                order = np.argsort(place, kind="stable")
                each, owner, place = each[order], owner[order], place[order]
                often = common_in_batch(each, min(hot, max(HOT_LEAST, int(len(firsts) * HOT_SHARE))))
                if len(often):
                    is_common = np.isin(each, often)
                    name, home_of = _named(each[is_common], place[is_common]), home[owner[is_common]]
                    back = np.argsort(home_of, kind="stable")
                    name, whose, home_of = name[back], digests[owner[is_common]][back], home_of[back]
                    cuts = _runs(home_of)
                    rows += [(int(home_of[lo]), COMMON, _pack(name[lo:hi], whose[lo:hi])) for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)]
                    at = np.flatnonzero(is_common)
                    at = at[np.unique(each[at], return_index=True)[1]]
                    for b in np.unique(place[at]).tolist():
                        rows.append((b, NAMES, _pack(_low(each[at][place[at] == b]))))
                    each, owner, place = each[~is_common], owner[~is_common], place[~is_common]
                cuts = _runs(place)
                for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                    runs = _short_runs(owner[lo:hi])
                    rows.append((int(place[lo]), SOME, _pack(_low(each[lo:hi]), digests[owner[lo:hi][runs[:-1]]], np.diff(runs).astype("u1"))))
            yield pd.DataFrame(rows, columns=["bucket", "kind", "payload"])

    return deal


def _rarity(df: np.ndarray) -> np.ndarray:
    """Document frequencies as 8 bits, in order: a sixteenth of an octave each up to 2**16, 255 beyond and for common shingles."""
    return np.minimum(np.floor(np.log2(df) * 16), 255).astype(np.uint8)


def _count(buckets: int):
    """Of one bucket's shingles: those of two nodes or more, sent to their nodes' buckets; documents and owners of common shingles are passed on."""

    def count(pdf: pd.DataFrame) -> pd.DataFrame:
        here = int(pdf["bucket"].iloc[0])
        rows = [(here, kind, p) for kind, p in zip(pdf["kind"].tolist(), pdf["payload"], strict=True) if kind in (DOCUMENTS, COMMON)]
        names = [_wide(_unpack(p, "u1")[0]) for p in pdf["payload"][pdf["kind"] == NAMES]]
        names = np.unique(np.concatenate(names)) if names else np.empty(0, np.uint64)
        tokens, digests = [], []
        for p in pdf["payload"][pdf["kind"] == SOME]:
            low, owner, n = _unpack(p, "u1", "<u8", "u1")
            tokens.append(_wide(low))
            digests.append(np.repeat(owner, n))
        if tokens:
            token, digest = np.concatenate(tokens), np.concatenate(digests)
            order = np.argsort(token)
            token, digest = token[order], digest[order]
            cuts = _runs(token)
            often = np.isin(token[cuts[:-1]], names) if len(names) else np.zeros(len(cuts) - 1, bool)
            many = np.repeat((np.diff(cuts) > 1) | often, np.diff(cuts))
            often = np.repeat(often, np.diff(cuts))
            token, digest, often = token[many], digest[many], often[many]
            order = np.lexsort((digest, token))
            token, digest, often = token[order], digest[order], often[order]
            fresh = np.ones(len(token), bool)
            fresh[1:] = (token[1:] != token[:-1]) | (digest[1:] != digest[:-1])
            token, digest, often = token[fresh], digest[fresh], often[fresh]
            cuts = _runs(token)
            rarity = np.where(often, 255, _rarity(np.repeat(np.diff(cuts), np.diff(cuts))))
            use = np.repeat(np.diff(cuts) > 1, np.diff(cuts)) | often
            token, digest, rarity = token[use], digest[use], rarity[use].astype(np.uint8)
            home = bucket_of(digest, buckets)
            order = np.lexsort((digest, home))
            token, digest, rarity, home = token[order], digest[order], rarity[order], home[order]
            cuts = _runs(home)
            for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                rows.append((int(home[lo]), SOME + here, _pack(_low(token[lo:hi]), digest[lo:hi], rarity[lo:hi])))
        return pd.DataFrame(rows, columns=["bucket", "kind", "payload"])

    return count


# --- 2. nodes that can have links ---

NODES = "kind int, doc_id long, gone boolean, digest long, size long, known int, level int, reach int, tokens binary"


def choose_level(size: int, known: int, rarity: np.ndarray) -> tuple[int, int]:
    """(matches asked for, known shingles in the prefix). rarity: of the known shingles, rarest first."""
    need = -(-OVER * size // UNDER)
    alone = size - known  # these stand first, and match nothing
    lists = np.concatenate(([0.0], np.cumsum(np.exp2(rarity.astype(np.float64) / 16) - 1)))
    best = None
    for level in LEVELS:
        if level > need:
            break
        reach = min(max(size - need + level - alone, 0), known)
        cost = LIST_COST * lists[reach] + VERIFY_COST * lists[reach] / level
        if best is None or cost < best[0]:
            best = (cost, level, reach)
    return best[1], best[2]


def _nodes(pdf: pd.DataFrame) -> pd.DataFrame:
    digest, ids, gone, size = _gathered(pdf["payload"][pdf["kind"] == DOCUMENTS], "<u8", "<i8", "u1", "<u4")
    rows = [(0, i, bool(g), d, n, 0, 0, 0, None) for d, i, g, n in zip(digest.view(np.int64).tolist(), ids.tolist(), gone.tolist(), size.tolist(), strict=True)]
    sizes = dict(zip(digest.tolist(), size.tolist(), strict=True))
    tokens, owners, rarities = [], [], []
    for from_, p in zip(pdf["kind"].tolist(), pdf["payload"], strict=True):
        if from_ >= SOME:
            low, owner, rarity = _unpack(p, "u1", "<u8", "u1")
            tokens.append(_named(_wide(low), from_ - SOME))
            owners.append(owner)
            rarities.append(rarity)
        elif from_ == COMMON:
            name, owner = _unpack(p, "<u8", "<u8")
            tokens.append(name)
            owners.append(owner)
            rarities.append(np.full(len(name), 255, np.uint8))
    if tokens:
        token, owner, rarity = np.concatenate(tokens), np.concatenate(owners), np.concatenate(rarities)
        order = np.lexsort((token, rarity, owner))
        token, owner, rarity = token[order], owner[order], rarity[order]
        fresh = np.ones(len(token), bool)  # a common shingle comes once from each batch that has its node
        fresh[1:] = (token[1:] != token[:-1]) | (owner[1:] != owner[:-1])
        token, owner, rarity = token[fresh], owner[fresh], rarity[fresh]
        cuts = _runs(owner)
        for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
            n, known = sizes[int(owner[lo])], hi - lo
            if UNDER * known >= OVER * n:
                level, reach = choose_level(n, known, rarity[lo:hi])
                rows.append((1, 0, False, int(owner[lo : lo + 1].view(np.int64)[0]), n, known, level, reach, token[lo:hi].tobytes()))
    return pd.DataFrame(rows, columns=[x.split()[0] for x in NODES.split(", ")])


# --- 3. candidates, links ---


def _post(buckets: int):
    """Prefix shingles of nodes, by bucket."""

    def post(batches):
        for pdf in batches:
            reach = pdf["reach"].to_numpy().astype(np.int64)
            token = np.concatenate([np.frombuffer(t, "<u8", r) for t, r in zip(pdf["tokens"], reach, strict=True)]) if len(pdf) else np.empty(0, np.uint64)
            node = np.repeat(np.arange(len(pdf)), reach)
            begins = np.cumsum(reach) - reach
            at = np.arange(len(token)) - np.repeat(begins, reach)  # among the node's known shingles
            place = ((token * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(32)) % np.uint64(buckets)).astype(np.int64)
            order = np.argsort(place, kind="stable")
            token, node, place, at = token[order], node[order], place[order], at[order].astype("<u4")
            digest, label = pdf["digest"].to_numpy().astype(np.int64), pdf["label"].to_numpy().astype(np.int64)
            size, known, level = (pdf[c].to_numpy().astype("<u4") for c in ("size", "known", "level"))
            cuts, rows = _runs(place), []
            for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                k = node[lo:hi]
                rows.append((int(place[lo]), _pack(token[lo:hi], digest[k], label[k], size[k], known[k], level[k], at[lo:hi])))
            yield pd.DataFrame(rows, columns=["bucket", "payload"])

    return post


PAIRS = "bucket int, part int, payload binary"
#: Parts of what pairing makes: pairs with their matches, and pairs of blocks of a long list, still to be paired.
FOUND, BLOCKS = 0, 1
_LIST = ("<i8", "<i8", "<u4", "<u4", "<u4", "<u4")  # digest, label, size, known, level, known shingles of the node before this one


class _Finder:
    """Candidate pairs of nodes, each once with its matches, held up to a bound and handed out packed by the second node's bucket."""

    def __init__(self, buckets: int, ordered: bool):
        self.buckets, self.ordered, self.found, self.held = buckets, ordered, [], 0

    def add(self, one, other) -> None:
        """one, other: columns of _LIST, row by row a pair. Known shingles have one order in all nodes: what two nodes share stands before this
        shingle in both, or from it on in both."""
        lo, hi = np.minimum(one[2], other[2]).astype(np.int64), np.maximum(one[2], other[2]).astype(np.int64)
        before, rest = np.minimum(one[5], other[5]).astype(np.int64), np.minimum(one[3].astype(np.int64) - one[5], other[3].astype(np.int64) - other[5])
        most = np.minimum(before + rest, lo)
        ok = np.flatnonzero((one[1] != other[1]) & (UNDER * lo >= OVER * hi) & (UNDER * most >= OVER * (lo + hi - most)))
        if len(ok):
            a, b = one[0][ok], other[0][ok]
            swap = a > b if self.ordered else np.zeros(len(ok), bool)
            self.found.append((np.where(swap, b, a), np.where(swap, a, b), np.ones(len(ok), np.int64), np.minimum(one[4][ok], other[4][ok])))
            self.held += len(ok)

    def packed(self, least: int = 0) -> pd.DataFrame | None:
        """What is held, once it is more than least pairs."""
        if self.held <= least:
            return None
        a, b, n, need = (np.concatenate([f[k] for f in self.found]) for k in range(4))
        order = np.lexsort((b, a))
        a, b, n, need = a[order], b[order], n[order], need[order]
        edge = np.ones(len(a), bool)
        edge[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1])
        at = np.flatnonzero(edge)
        a, b, n, need = a[at], b[at], np.add.reduceat(n, at), need[at]
        if len(a) <= least // 2:  # mostly repeats: hold on
            self.found, self.held = [(a, b, n, need)], len(a)
            return None
        self.found, self.held, rows = [], 0, []
        place = bucket_of(b.view(np.uint64), self.buckets)
        order = np.argsort(place, kind="stable")
        a, b, n, need, place = a[order], b[order], n[order], need[order], place[order]
        ends = _runs(place)
        for lo, hi in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True):
            rows.append((int(place[lo]), FOUND, _pack(a[lo:hi], b[lo:hi], n[lo:hi].astype("<u4"), need[lo:hi].astype("<u4"))))
        return pd.DataFrame(rows, columns=["bucket", "part", "payload"])


def _some_pairs(finder: _Finder, one: list, other: list | None, held: int):
    """All pairs of two blocks, or within one, some rows of their table at a time."""
    n, m = len(one[0]), len((other or one)[0])
    step = max(1, 500_000 // max(m, 1))
    for at in range(0, n, step):
        if other is None:
            i, j = np.triu_indices(min(step, n - at), 1, n - at)
            i, j = i + at, j + at
        else:
            i, j = np.repeat(np.arange(at, min(at + step, n)), m), np.tile(np.arange(m), min(step, n - at))
        finder.add([c[i] for c in one], [c[j] for c in other or one])
        if (out := finder.packed(held)) is not None:
            yield out


def _pairs(buckets: int, star: int | None, list_nodes: int = LIST_NODES, held: int = HELD_PAIRS):
    """Of one bucket's lists: candidate pairs of different components with their matches, by the second node's bucket.

    star: the rank of the list's fullest nodes that is paired with all others; None: all pairs. Lists of more than list_nodes are
    then cut into blocks, and each pair of blocks is a row of its own.
    """

    def pairs(pdfs: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        token, digest, label, size, known, level, before = _gathered([p for pdf in pdfs for p in pdf["payload"]], "<u8", *_LIST)
        size, known = size.astype(np.int64), known.astype(np.int64)
        # the fullest nodes of a list come first: those with the least share of shingles of their own, then by digest
        share = (known << 20) // np.maximum(size, 1)
        order = np.lexsort((digest, -share, token))
        token = token[order]
        columns = [c[order] for c in (digest, label, size, known, level, before)]
        cuts, finder = _runs(token), _Finder(buckets, star is None)
        lengths = np.diff(cuts)
        if star is not None:
            head = np.repeat(cuts[:-1] + star, lengths)
            use = np.flatnonzero(np.repeat(lengths > star + (star == 0), lengths) & (head != np.arange(len(token))))
            for at in range(0, len(use), 500_000):
                part = use[at : at + 500_000]
                finder.add([c[head[part]] for c in columns], [c[part] for c in columns])
                if (out := finder.packed(held)) is not None:
                    yield out
        else:
            for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                mine = [c[lo:hi] for c in columns]
                if hi - lo < 2 or (mine[1] == mine[1][0]).all():
                    continue
                if hi - lo <= list_nodes:
                    yield from _some_pairs(finder, mine, None, held)
                    continue
                wide = max(list_nodes, -(-(hi - lo) // MOST_BLOCKS))
                blocks = [[c[at : at + wide].astype(t) for c, t in zip(mine, _LIST, strict=True)] for at in range(0, hi - lo, wide)]
                for x, one in enumerate(blocks):
                    rows = []
                    for y in range(x, len(blocks)):
                        other = blocks[y] if y > x else [c[:0] for c in one]
                        rows.append((int((int(token[lo]) * 31 + x * MOST_BLOCKS + y) % 0x7FFFFFFF), BLOCKS, _pack(*one, *other)))
                    yield pd.DataFrame(rows, columns=["bucket", "part", "payload"])
        if (out := finder.packed()) is not None:
            yield out

    return pairs


def _block_pairs(buckets: int, held: int = HELD_PAIRS):
    """Candidate pairs of pairs of blocks: each row by itself."""

    def pairs(batches):
        for pdf in batches:
            finder = _Finder(buckets, True)
            for p in pdf["payload"]:
                got = _unpack(p, *_LIST, *_LIST)
                yield from _some_pairs(finder, got[: len(_LIST)], got[len(_LIST) :] if len(got[len(_LIST)]) else None, held)
            if (out := finder.packed()) is not None:
                yield out

    return pairs


def _wanted(star: bool):
    """Pairs of a share, or several, of one bucket that are to be verified, packed; and a row for each node whose shingles that takes."""

    def wanted(pdf: pd.DataFrame) -> pd.DataFrame:
        a, b, n, need = _gathered(pdf["payload"], "<i8", "<i8", "<u4", "<u4")
        order = np.lexsort((b, a))
        a, b, n, need = a[order], b[order], n[order].astype(np.int64), need[order]
        edge = np.ones(len(a), bool)
        edge[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1])
        at = np.flatnonzero(edge)
        a, b, n, need = a[at], b[at], np.add.reduceat(n, at) if len(at) else n, need[at]
        if star:  # of each second node, the partner with the most matches
            order = np.lexsort((a, -n, b))
            a, b = a[order], b[order]
            first = np.ones(len(b), bool)
            first[1:] = b[1:] != b[:-1]
            a, b = a[first], b[first]
        else:
            a, b = a[n >= need], b[n >= need]
        here = int(pdf["bucket"].iloc[0]) // SHARES
        rows = [(here, 0, _pack(a, b))] if len(a) else []
        rows += [(here, d, None) for d in np.unique(np.concatenate((a, b))).tolist()]
        return pd.DataFrame(rows, columns=["bucket", "digest", "pairs"])

    return wanted


class _Sets:
    """Nodes' shingles, as arrays over what came in; as sets only so many at once."""

    def __init__(self, rows):
        self.arrays = {int(d): (np.frombuffer(t, "<u8"), int(n)) for d, t, n in rows}
        self.sets, self.held = {}, 0

    def of(self, node: int) -> set:
        got = self.sets.get(node)
        if got is None:
            if self.held > SET_TOKENS:
                self.sets.clear()
                self.held = 0
            got = self.sets[node] = set(self.arrays[node][0].tolist())
            self.held += len(got)
        return got

    def linked(self, x: int, y: int) -> bool:
        (s, n), (t, m) = self.arrays[x], self.arrays[y]
        if max(len(s), len(t)) > LONG_SET:
            return enough(len(np.intersect1d(s, t)), n, m)
        return enough(len(self.of(x) & self.of(y)), n, m)


def _verify(pdf: pd.DataFrame) -> pd.DataFrame:
    """The links among one bucket's pairs."""
    has = pdf["tokens"].notna()
    sets = _Sets(zip(pdf["digest"][has], pdf["tokens"][has], pdf["size"][has], strict=True))
    out = []
    for p in pdf["pairs"][pdf["pairs"].notna()]:
        a, b = _unpack(p, "<i8", "<i8")
        out += [(x, y) for x, y in zip(a.tolist(), b.tolist(), strict=True) if sets.linked(x, y)]
    return pd.DataFrame(out, columns=["u", "v"], dtype="int64")


def bucket_count(text_bytes: int) -> int:
    return min(max(LEAST_BUCKETS, -(-text_bytes // BUCKET_BYTES)), MOST_BUCKETS)


def part_counts(nodes: DataFrame) -> tuple[int, int]:
    """Buckets of lists and of verifications for nodes: the planner's size of a table says nothing of its packed columns, so that these are summed."""
    known, reach = nodes.agg(F.sum("known"), F.sum("reach")).first()
    return max(LEAST_BUCKETS, -(-40 * (reach or 0) // LIST_BYTES)), max(LEAST_BUCKETS, -(-8 * (known or 0) // SET_BYTES))


def _by_bucket(df: DataFrame, buckets: int):
    """df grouped by bucket; dealt out by the bucket's number itself, where hashing would put several buckets into one task and none into others."""
    return (df.repartitionById(buckets, "bucket") if buckets <= MOST_TASKS else df).groupBy("bucket")


def link_classes(docs: DataFrame, star_rounds: int = STAR_ROUNDS, id_col: str = "doc_id", text_col: str = "text", list_nodes: int = LIST_NODES, hot: int | None = None, held: int = HELD_PAIRS) -> DataFrame:
    """doc_id, n_shingles, component_id of every row. list_nodes: nodes of a prefix list from which it is paired block by block. held:
    pairs that a task holds before it hands them on. hot: texts of a batch from which a shingle is common in it, whatever its share (None: by the number of batches)."""
    src = docs.select(*common.id_and_gone(id_col), common.whole_text(docs, text_col).alias("text"))
    # the planner takes a text for 20 bytes beside the other columns: by its size of src, buckets would grow with what isn't read
    text_bytes = src.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = bucket_count(text_bytes)
    sent = src.mapInPandas(_deal(buckets, max(HOT_LEAST, HOT_ENTRIES // max(1, -(-text_bytes // PORTION))) if hot is None else hot), SENT)
    counted = _by_bucket(sent, buckets).applyInPandas(_count(buckets), SENT)
    told = common.keep(_by_bucket(counted, buckets).applyInPandas(_nodes, NODES), "nodes")
    rows = told.where("kind = 0").select(F.when(~F.col("gone"), F.col("doc_id")).alias("doc_id"), "digest", "size")
    nodes = told.where("kind = 1").drop("kind", "doc_id", "gone")
    firsts = rows.where("size > 0").groupBy("digest").agg(F.min("doc_id").alias("least"))
    # the label of a node: the least id of its component so far; an unnamed node is labelled below all ids
    labels = common.keep(nodes.select("digest").join(firsts, "digest").select("digest", F.coalesce("least", F.col("digest").bitwiseOR(F.lit(-(1 << 63)))).alias("label")), "labels")
    parts, sets_parts = part_counts(nodes)
    for star in [*range(star_rounds), None]:
        posted = nodes.join(labels, "digest").mapInPandas(_post(parts), "bucket int, payload binary")
        pairs = posted.groupBy("bucket").applyInPandas(_pairs(sets_parts * SHARES, star, list_nodes, held), PAIRS)
        merged = SHARES  # that many shares at once: the pairs of a star round are no more than the lists' entries
        if star is None:
            pairs = common.keep(pairs, "blocks")  # what each list's task makes, before the blocks are dealt out
            size = {r["part"]: r["n"] for r in pairs.groupBy("part").agg(F.sum(F.length("payload")).alias("n")).collect()}
            blocks = pairs.where(F.col("part") == BLOCKS)
            pairs = pairs.where(F.col("part") == FOUND)
            if BLOCKS in size:  # how many pairs they make isn't known yet
                tasks = max(LEAST_BUCKETS, -(-size[BLOCKS] // BUCKET_BYTES))
                pairs = pairs.unionByName(blocks.repartition(tasks, "bucket").mapInPandas(_block_pairs(sets_parts * SHARES, held), PAIRS))
                merged = 1
            while merged > 1 and size.get(FOUND, 0) * merged > PAIR_BYTES * sets_parts * SHARES:
                merged //= 2
        wanted = common.keep(pairs.groupBy(F.floor(F.col("bucket") / merged)).applyInPandas(_wanted(star is not None), "bucket int, digest long, pairs binary"), "pairs")
        if wanted.isEmpty():
            if star is None:
                break
            continue
        sets = wanted.where("pairs is null").select("bucket", "digest").distinct().join(nodes.select("digest", "size", "tokens"), "digest")
        both = sets.select("bucket", "digest", "size", "tokens", F.lit(None).cast("binary").alias("pairs")).unionByName(wanted.where("pairs is not null").select("bucket", F.lit(0).cast("long").alias("digest"), F.lit(0).cast("long").alias("size"), F.lit(None).cast("binary").alias("tokens"), "pairs"))
        links = both.groupBy("bucket").applyInPandas(_verify, "u long, v long")
        named = links.join(labels.select(F.col("digest").alias("u"), F.col("label").alias("lu")), "u").join(labels.select(F.col("digest").alias("v"), F.col("label").alias("lv")), "v")
        roots = components(named.select(F.col("lu").alias("u"), F.col("lv").alias("v")))
        labels = common.keep(labels.join(roots, labels["label"] == roots["node"], "left").select("digest", F.coalesce("root", "label").alias("label")), "labels")
    owner = firsts.join(labels, "digest", "left").select("digest", F.coalesce("label", "least").alias("component_id"))
    named = rows.where("size > 0").join(owner, "digest").select("doc_id", "size", "component_id")
    out = named.unionByName(rows.where("size = 0").select("doc_id", "size", F.col("doc_id").alias("component_id")))
    return out.select("doc_id", F.col("size").alias("n_shingles"), F.when(F.col("component_id") < -(1 << 62), F.lit(None)).otherwise(F.col("component_id")).alias("component_id"))


def one_of_each_class(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with one row of each class, that of the least id. Rows without an id cannot be named by a class, and stay."""
    classes = link_classes(docs, id_col=id_col, text_col=text_col)
    stays, n = common.fresh(docs, "stays", "n")
    stay = classes.where("doc_id = component_id").select(F.col("doc_id").alias(stays)).distinct()
    kept = docs.where(F.col(id_col).isNotNull()).join(stay, F.col(id_col).cast("long") == F.col(stays), "left_semi")
    # rows equal in id and text stand for one another; other texts of the same id are classes of their own
    order = Window.partitionBy(id_col, F.xxhash64(text_col)).orderBy(F.lit(0))
    once = kept.withColumn(n, F.row_number().over(order)).where(F.col(n) == 1).drop(n)
    return once.unionByName(docs.where(F.col(id_col).isNull()))


def op2_adaptive_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link_classes(common.documents(spark, sf_dir))


#: The same for DuckDB, from the definition.
OP2_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS a FROM documents),
s AS (
  SELECT doc_id, list_distinct(list_transform(range(1, len(a) - 3), lambda i: array_to_string(a[i:i + 4], ' '))) AS g FROM w WHERE len(a) >= 5
  UNION ALL SELECT doc_id, [array_to_string(a, ' ')] FROM w WHERE len(a) BETWEEN 1 AND 4
  UNION ALL SELECT doc_id, [] FROM w WHERE len(a) = 0),
e AS (SELECT doc_id, len(g) AS n, unnest(g) AS h FROM s),
p AS (SELECT x.doc_id AS u, y.doc_id AS v FROM e x JOIN e y ON x.h = y.h AND x.doc_id <> y.doc_id
  GROUP BY x.doc_id, y.doc_id, x.n, y.n HAVING 100 * count(*) >= 75 * (x.n + y.n - count(*))),
r AS (SELECT doc_id AS node, doc_id AS root FROM documents UNION SELECT p.v, r.root FROM r JOIN p ON p.u = r.node WHERE r.root < p.v)
SELECT s.doc_id, len(s.g) AS n_shingles, least(s.doc_id, coalesce(m.root, s.doc_id)) AS component_id
FROM s LEFT JOIN (SELECT node, min(root) AS root FROM r GROUP BY node) m ON m.node = s.doc_id
"""
