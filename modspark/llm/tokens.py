"""Splitting and merging of text into token ids, exactly as the tokenizer files say.

``LexiconCoder``: a minimal acyclic transducer holds frequent words with their ids as outputs. Words with equal endings share
states; an id sequence is found through a minimal perfect hash (each arc carries the number of words that sort before it).
The automaton and its outputs are flat arrays in one file in memory, which each Python worker maps. A word
that the lexicon lacks is merged pair by pair, by rank, and kept in a bounded table.

``ByteCoder``: the byte-level file. Many texts at once are split, and their distinct pieces merged round by round, as arrays
(``PieceRounds``); what these don't cover goes through the library's model, with the same bounded table.
"""

from __future__ import annotations

import json
import mmap
import os
import re
import unicodedata
from array import array
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from tokenizers import Tokenizer

#: Words whose codes a worker keeps at once.
KEPT_WORDS = 100_000
#: Pieces of a byte-level file in each of a worker's two generations.
KEPT_PIECES = 200_000
#: Characters of texts that are split and merged as arrays at once (a longer text is by itself), and bytes of the longest piece merged so.
CHUNK_CHARS = 8 << 20
LONG_PIECE = 64


@lru_cache(maxsize=1)
def byte_signs() -> list[str]:
    """The printable sign that stands for each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    signs, n = {b: chr(b) for b in plain}, 256
    for b in range(256):
        if b not in signs:
            signs[b] = chr(n)
            n += 1
    return [signs[b] for b in range(256)]


def signed(word: str, _table={b: s for b, s in enumerate(byte_signs())}) -> str:  # noqa: B006, C416  a constant
    """The word's bytes as signs."""
    return word.encode("utf-8", "surrogatepass").decode("latin-1").translate(_table)


class Merger:
    """Ranked pair merges of one vocabulary file, spelled out: what the library's compiled model does, to test it against."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        self.vocab: dict[str, int] = model["vocab"]
        self.end: str = model["end_of_word_suffix"] or ""
        pairs = [tuple(x) if isinstance(x, list) else tuple(x.split(" ")) for x in model["merges"]]
        self.ranks = {p: i for i, p in enumerate(pairs)}

    def pieces(self, word: str) -> list[str]:
        """The pieces of a word that is written in byte signs: the lowest-ranked pair is merged first, leftmost first."""
        parts = list(word)
        if parts and self.end:
            parts[-1] += self.end
        get, none = self.ranks.get, len(self.ranks)
        while len(parts) > 1:
            best = min((get(p, none) for p in zip(parts, parts[1:], strict=False)), default=none)
            if best == none:
                break
            out, i, n = [], 0, len(parts)
            while i < n:
                if i + 1 < n and get((parts[i], parts[i + 1])) == best:
                    out.append(parts[i] + parts[i + 1])
                    i += 2
                else:
                    out.append(parts[i])
                    i += 1
            parts = out
        return parts

    def ids(self, word: str) -> list[int]:
        """Pieces that the vocabulary lacks give nothing, as in a model without an unknown token."""
        get = self.vocab.get
        return [i for p in self.pieces(word) if (i := get(p)) is not None]


class Transducer:
    """A minimal acyclic automaton over byte strings, each word with a number; built from sorted words.

    Arrays: first[state] .. first[state + 1] are the arcs of a state; label, target and before of each arc, before being the
    number of accepted words that precede those through the arc; final[state].
    """

    FIELDS = ("first", "label", "target", "before", "final")

    def __init__(self, **arrays: np.ndarray):
        for k in self.FIELDS:
            setattr(self, k, arrays[k])
        self._labels = arrays["label"].tobytes()
        self._views = [memoryview(np.ascontiguousarray(arrays[k])) for k in ("first", "target", "before")]

    @classmethod
    def build(cls, words: list[bytes]) -> Transducer:
        """words: sorted, distinct. States are frozen as soon as no later word can reach them, equal ones shared."""
        known: dict[tuple, int] = {}
        states: list[tuple[bool, tuple[tuple[int, int], ...]]] = []
        counts: list[int] = []

        def freeze(final: bool, arcs: list[tuple[int, int]]) -> int:
            key = (final, tuple(arcs))
            at = known.get(key)
            if at is None:
                at = known[key] = len(states)
                states.append(key)
                counts.append(final + sum(counts[t] for _, t in arcs))
            return at

        open_: list[list] = [[False, [], -1]]  # final, arcs, label from the parent
        before = b""
        for word in words:
            same = len(os.path.commonprefix([before, word]))
            while len(open_) > same + 1:
                final, arcs, label = open_.pop()
                open_[-1][1].append((label, freeze(final, arcs)))
            for c in word[same:]:
                open_.append([False, [], c])
            open_[-1][0] = True
            before = word
        while len(open_) > 1:
            final, arcs, label = open_.pop()
            open_[-1][1].append((label, freeze(final, arcs)))
        root = freeze(open_[0][0], open_[0][1])
        order = [root, *(s for s in range(len(states)) if s != root)]  # the root is state 0
        place = {s: i for i, s in enumerate(order)}
        first, label, target, ahead, final = [0], [], [], [], []
        for s in order:
            fin, arcs = states[s]
            n = int(fin)
            for c, t in arcs:
                label.append(c)
                target.append(place[t])
                ahead.append(n)
                n += counts[t]
            first.append(len(label))
            final.append(fin)
        return cls(first=np.array(first, "<u4"), label=np.array(label, "u1"), target=np.array(target, "<u4"), before=np.array(ahead, "<u4"), final=np.array(final, "u1"))

    def number(self, word: bytes) -> int:
        """The word's place among the sorted words; -1 if it isn't accepted."""
        state, n, find = 0, 0, self._labels.find
        first, target, before = self._views
        for c in word:
            arc = find(c, first[state], first[state + 1])
            if arc < 0:
                return -1
            n += before[arc]
            state = target[arc]
        return n if self.final[state] else -1


MAGIC = b"lexicon1"


def pack_lexicon(words: dict[str, list[int]]) -> bytes:
    """The file: magic, a JSON line with each array's type, place and length, the arrays."""
    order = sorted((w.encode("utf-8"), ids) for w, ids in words.items())
    auto = Transducer.build([w for w, _ in order])
    arrays = {k: getattr(auto, k) for k in Transducer.FIELDS}
    arrays["out_first"] = np.cumsum([0, *(len(i) for _, i in order)]).astype("<u4")
    arrays["out_ids"] = np.array([x for _, i in order for x in i], "<u4")
    head, at = {}, 0
    for k, v in arrays.items():
        head[k] = [v.dtype.str, at, len(v)]
        at += -(-v.nbytes // 8) * 8
    line = json.dumps(head).encode()
    line += b" " * (-(len(MAGIC) + 4 + len(line)) % 8)
    return MAGIC + len(line).to_bytes(4, "little") + line + b"".join(v.tobytes() + b"\0" * (-v.nbytes % 8) for v in arrays.values())


class Lexicon:
    """The memory-mapped file."""

    def __init__(self, buffer):
        if bytes(buffer[:8]) != MAGIC:
            raise ValueError("no lexicon file")
        n = int.from_bytes(buffer[8:12], "little")
        head = json.loads(bytes(buffer[12 : 12 + n]))
        arrays = {k: np.frombuffer(buffer, t, m, 12 + n + at) for k, (t, at, m) in head.items()}
        self.auto = Transducer(**{k: arrays[k] for k in Transducer.FIELDS})
        self.out_first, self.out_ids = arrays["out_first"], arrays["out_ids"]

    @classmethod
    def mapped(cls, blob: bytes) -> Lexicon:
        """Maps the bytes of a lexicon file from a file in memory, which no folder holds: it goes with its worker."""
        with open(os.memfd_create("lexicon"), "wb+") as f:
            f.write(blob)
            f.flush()
            return cls(mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ))

    def ids(self, word: str) -> np.ndarray | None:
        n = self.auto.number(word.encode("utf-8"))
        return None if n < 0 else self.out_ids[self.out_first[n] : self.out_first[n + 1]]


class _Codes(dict):
    """word -> code, made on demand; emptied when full."""

    def __init__(self, make, most: int = KEPT_WORDS):
        super().__init__()
        self.make, self.most = make, most

    def __missing__(self, word):
        if len(self) >= self.most:
            self.clear()
        got = self[word] = self.make(word)
        return got


class _AgedCodes(_Codes):
    """_Codes in two generations: when the newer one is full it becomes the older, from which words that come up again return."""

    def __init__(self, make, most: int = KEPT_PIECES):
        super().__init__(make, most)
        self.old: dict = {}

    def __missing__(self, word):
        if len(self) >= self.most:
            self.old = dict(self)
            self.clear()
        got = self.old.get(word)
        if got is None:
            got = self.make(word)
        self[word] = got
        return got


#: The split rule of word_bpe_49k.json, in general and for texts of plain letters.
WORD_RULE = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\p{White_Space}\p{L}\p{N}]+")
#: Letters and digits up to U+024F by their categories; a text of these and ASCII signs alone splits alike by the faster rule.
LETTERS = "A-Za-zªµºÀ-ÖØ-öø-ɏ"
DIGITS = "0-9²³¹¼-¾"
UNUSUAL = re.compile("[^\t-\r -ɏ]|[\u0080-\u009f­]")
FAST_WORD_RULE = re.compile(f"'(?:[stmd]|re|ve|ll)|[{LETTERS}]+|[{DIGITS}]|[^ \t-\r\u0085 {LETTERS}{DIGITS}]+")
#: Fixed value: the split rule of byte-level files.
BYTE_RULE = regex.compile(r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+""")
_GAP = " \t-\r\u0085 "
FAST_BYTE_RULE = re.compile(f"'(?:[stmd]|re|ve|ll)| ?[{LETTERS}]+| ?[{DIGITS}]+| ?[^{_GAP}{LETTERS}{DIGITS}]+|[{_GAP}]+(?![^{_GAP}])|[{_GAP}]+")


def usual(text: str) -> bool:
    """Whether the faster rules split the text as the general ones do; ASCII needs no look at every character."""
    if text.isascii() and not any(c in text for c in "\x1c\x1d\x1e\x1f"):
        return True
    return not UNUSUAL.search(text)


@lru_cache(maxsize=1)
def unassigned() -> re.Pattern:
    """Code points without a category: what they count as differs between versions of the tables that rules are made of."""
    cuts, inside = [], False
    for cp in range(0x110000):
        none = unicodedata.category(chr(cp)) == "Cn"
        if none != inside:
            cuts.append(cp - inside)
            inside = none
    cuts += [0x10FFFF] if inside else []
    return re.compile("[" + "".join(f"\\U{a:08x}-\\U{b:08x}" for a, b in zip(cuts[::2], cuts[1::2], strict=True)) + "]")


@lru_cache(maxsize=1)
def _word_file(path: str) -> tuple[Tokenizer, dict[str, int], re.Pattern, dict[int, str]]:
    """A word-level file's library model, added tokens, the rule that cuts these out, and pieces by id; once for all coders of a worker."""
    with open(path, encoding="utf-8") as f:
        told = json.load(f)
    added = {x["content"]: x["id"] for x in told["added_tokens"]}
    if any(x["single_word"] or x["lstrip"] or x["rstrip"] or x["normalized"] for x in told["added_tokens"]):
        raise ValueError("added tokens that take in what is beside them, or are looked for in normalised text")
    parts = re.compile("(" + "|".join(map(re.escape, sorted(added, key=len, reverse=True))) + ")") if added else re.compile("(?!)")
    return Tokenizer.from_file(path), added, parts, {i: p for p, i in told["model"]["vocab"].items()}


class LexiconCoder:
    """word_bpe: normalises, splits, looks words up, merges the rest; decodes as the library's ids-to-text does.

    Each distinct word that a worker meets goes through the automaton, and through the merges if that lacks it; a bounded table keeps
    what they gave. Texts of any script are split here, added tokens apart; only what lies between code points that
    no table knows (``unassigned``) is left to the library, piece by piece.
    """

    def __init__(self, path: str, lexicon: Lexicon | None = None):
        self.lexicon = lexicon
        self.library, self.added, self.parts, self.names = _word_file(path)
        self.signs = byte_signs()
        self.merge = self.library.model.tokenize
        self.codes = _Codes(self._code)

    def merged_ids(self, word: str) -> list[int]:
        """Ids of a word by the ranked merges of the file's model."""
        return [x.id for x in self.merge(signed(word))]

    def word_ids(self, word: str) -> list[int]:
        """Ids of one split word: the lexicon's, else merged."""
        if self.lexicon is not None:
            got = self.lexicon.ids(word)
            if got is not None:
                return got.tolist()
        return self.merged_ids(word)

    def _code(self, word: str) -> tuple[bytes, str]:
        ids = self.word_ids(word)
        return array("I", ids).tobytes(), "".join([" " + self.names[i] for i in ids])

    def _split(self, text: str) -> list[str] | None:
        """The words of a text without added tokens; None where only the library knows them."""
        if usual(text):
            return FAST_WORD_RULE.findall(unicodedata.normalize("NFC", text).lower())
        if unassigned().search(text):
            return None
        return WORD_RULE.findall(self.library.normalizer.normalize_str(text))

    def words(self, text: str) -> list[str]:
        """The words that are looked up; those of pieces that go to the library are left out."""
        if not any(x in text for x in self.added):
            return self._split(text) or []
        return [w for part in self.parts.split(text) if part and part not in self.added for w in self._split(part) or ()]

    def _piece(self, text: str) -> tuple[bytes, str]:
        words = self._split(text)
        if words is None:
            ids = self.library.encode(text, add_special_tokens=False).ids
            return array("I", ids).tobytes(), "".join([" " + self.names[i] for i in ids])
        codes = self.codes
        got = [codes[w] for w in words]
        return b"".join([a for a, _ in got]), "".join([b for _, b in got])

    def encode(self, text: str) -> tuple[bytes, str]:
        """Ids as little-endian 32-bit integers, and the text they decode to."""
        if not any(x in text for x in self.added):
            ids, said = self._piece(text)
            return ids, said[1:]
        got = [(array("I", [self.added[x]]).tobytes(), " " + x) if x in self.added else self._piece(x) for x in self.parts.split(text) if x]
        return b"".join([a for a, _ in got]), "".join([b for _, b in got])[1:]


#: Kinds of code points up to U+024F, as FAST_BYTE_RULE tells them apart; CUT stands between texts.
LETTER, DIGIT, GAP, OTHER, CUT = range(5)


@lru_cache(maxsize=1)
def _kinds() -> np.ndarray:
    sets = [(LETTER, re.compile(f"[{LETTERS}]")), (DIGIT, re.compile(f"[{DIGITS}]")), (GAP, re.compile(f"[{_GAP}]"))]
    return np.array([next((k for k, found in sets if found.match(chr(c))), OTHER) for c in range(0x250)], np.uint8)


def piece_starts(texts: list[str]) -> tuple[bytes, np.ndarray, np.ndarray]:
    """FAST_BYTE_RULE as arrays, for texts that are usual: all bytes with one byte after each text; where pieces start, and
    which of them are the bytes after a text."""
    raw = [t.encode("utf-8") for t in texts]
    data = b"\n".join([*raw, b""])
    chars, kinds = np.frombuffer(data, np.uint8), _kinds()
    cuts = np.cumsum([len(r) + 1 for r in raw]) - 1
    kind = np.concatenate((kinds[:128], np.zeros(128, np.uint8)))[chars]
    high = np.flatnonzero(chars >= 0x80)
    lead = high[::2]  # usual texts have two bytes a character there
    kind[lead] = kind[lead + 1] = kinds[(chars[lead].astype(np.int64) & 31) << 6 | chars[lead + 1] & 63]
    kind[cuts] = CUT
    start = np.ones(len(chars), bool)
    np.not_equal(kind[1:], kind[:-1], out=start[1:])
    start[cuts] = True
    start[cuts[:-1] + 1] = True
    # a run of white space leaves its last character to what follows: before it if that is a space, else by itself
    runs = np.flatnonzero(start[1:] & (kind[:-1] == GAP) & (kind[1:] != CUT)) + 1
    start[runs - 1 - (chars[runs - 1] >= 0x80)] = True
    start[runs[chars[runs - 1] == 32]] = False
    # an apostrophe where a piece starts takes an ending with it
    marks = np.flatnonzero((chars == 39) & start)
    if len(marks):
        one = chars[np.minimum(marks + 1, len(chars) - 1)]
        two = chars[np.minimum(marks + 2, len(chars) - 1)]
        short = np.isin(one, np.frombuffer(b"stmd", np.uint8))
        long = ((one == 114) | (one == 118)) & (two == 101) | (one == 108) & (two == 108)
        start[marks[short | long] + 1] = False
        start[marks[short] + 2] = True
        start[marks[long] + 3] = True
    at = np.flatnonzero(start)
    return data, at, np.searchsorted(at, cuts)


class PieceRounds:
    """Ranked pair merges of many distinct pieces at once: in a round each piece merges its lowest-ranked pair, wherever that stands.

    That is the merges' own order if no merge makes a pair of a lower rank than its own: a token comes from one merge, after
    those of its parts. ``fits`` says whether a file is of this form.
    """

    NONE = np.int32(2**31 - 1)

    def __init__(self, model: dict):
        vocab = model["vocab"]
        pairs = [tuple(x) if isinstance(x, list) else tuple(x.split(" ")) for x in model["merges"]]
        plain = not any(model.get(k) for k in ("dropout", "continuing_subword_prefix", "end_of_word_suffix", "ignore_merges", "byte_fallback"))
        self.fits = bool(pairs) and plain and all(s in vocab for s in byte_signs()) and all(a in vocab and b in vocab and a + b in vocab for a, b in pairs)
        if not self.fits:
            return
        self.base = np.array([vocab[s] for s in byte_signs()], np.int32)
        left, right, self.made = (np.array([vocab[x] for x in side], np.int64) for side in ([a for a, _ in pairs], [b for _, b in pairs], [a + b for a, b in pairs]))
        born = np.full(max(vocab.values()) + 1, len(pairs), np.int64)
        born[self.base] = -1
        once = len(set(self.made.tolist())) == len(pairs) and not np.isin(self.made, self.base).any()
        born[self.made] = np.arange(len(pairs))
        self.fits = once and bool((np.maximum(born[left], born[right]) < np.arange(len(pairs))).all())
        # pair -> rank: open addressing, a fifth full at most
        self.bits = int(np.ceil(np.log2(5 * len(pairs))))
        self.keys, self.ranks = np.full(1 << self.bits, -1, np.int64), np.full(1 << self.bits, self.NONE, np.int32)
        keys = left << 32 | right
        for rank, (key, at) in enumerate(zip(keys.tolist(), self._slot(keys).tolist(), strict=True)):
            while self.keys[at] >= 0:
                at = (at + 1) & ((1 << self.bits) - 1)
            self.keys[at], self.ranks[at] = key, rank
        self.first = self.rank(np.repeat(self.base, 256), np.tile(self.base, 256)).reshape(256, 256)

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return (keys.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - self.bits)).view(np.int64)

    def rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Ranks of pairs of ids; NONE where they don't merge."""
        keys = left.astype(np.int64) << 32 | right
        at = self._slot(keys)
        there = self.keys[at]
        out = np.where(there == keys, self.ranks[at], self.NONE)
        open_ = np.flatnonzero((there != keys) & (there >= 0))
        while len(open_):
            at[open_] = (at[open_] + 1) & ((1 << self.bits) - 1)
            there = self.keys[at[open_]]
            same = there == keys[open_]
            out[open_[same]] = self.ranks[at[open_[same]]]
            open_ = open_[~same & (there >= 0)]
        return out

    def ids(self, chars: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Pieces as bytes in a row, with their sizes (none is 0): ids, and where in them each piece's begin and how many they are."""
        begin, many = np.zeros(len(sizes), np.int64), np.zeros(len(sizes), np.int64)
        if not len(sizes):
            return np.zeros(0, np.int32), begin, many
        number, done, n_done = np.arange(len(sizes)), [], 0
        now = self.base[chars]
        at = np.cumsum(sizes) - sizes
        head = np.zeros(len(now) + 1, bool)
        head[at] = head[-1] = True
        rank = np.full(len(now), self.NONE, np.int32)
        rank[:-1] = self.first[chars[:-1], chars[1:]]
        rank[head[1:]] = self.NONE
        while True:
            best = np.minimum.reduceat(rank, at)
            over = best == self.NONE
            if over.any():
                gone = np.repeat(over, sizes)
                done.append(now[gone])
                many[number[over]] = sizes[over]
                begin[number[over]] = n_done + np.cumsum(sizes[over]) - sizes[over]
                n_done += len(done[-1])
                if len(done[-1]) == len(now):
                    return np.concatenate(done), begin, many
                stay = ~gone
                now, rank, head = now[stay], rank[stay], np.append(head[:-1][stay], True)
                number, sizes, best = number[~over], sizes[~over], best[~over]
            place = np.flatnonzero(rank == np.repeat(best, sizes))
            # x x x: the leftmost pair first, so every second place of a run
            count = np.arange(len(place))
            broken = np.ones(len(place), bool)
            np.not_equal(np.diff(place), 1, out=broken[1:])
            place = place[(count - np.maximum.accumulate(np.where(broken, count, 0))) % 2 == 0]
            now[place] = self.made[rank[place]]
            stay = np.ones(len(now), bool)
            stay[place + 1] = False
            now, rank, head = now[stay], rank[stay], np.append(head[:-1][stay], True)
            place -= np.arange(len(place))
            at = np.flatnonzero(head)
            sizes, at = np.diff(at), at[:-1]
            near = np.concatenate((place, place[~head[place]] - 1))
            ends = head[near + 1]
            rank[near[ends]] = self.NONE
            near = near[~ends]
            rank[near] = self.rank(now[near], now[near + 1])


class ByteCoder:
    """byte_bpe: ids of a text as 32-bit integers."""

    def __init__(self, path: str):
        self.signs = byte_signs()
        self.library = Tokenizer.from_file(path)
        self.merge = self.library.model.tokenize
        with open(path, encoding="utf-8") as f:
            told = json.load(f)
        self.added = [x["content"] for x in told["added_tokens"]]
        self.codes = _AgedCodes(self._code)
        self.rounds = PieceRounds(told["model"])

    def _code(self, piece: str) -> bytes:
        return array("I", [x.id for x in self.merge(signed(piece))]).tobytes()

    def encode(self, text: str) -> bytes:
        if any(x in text for x in self.added):
            return array("I", self.library.encode(text, add_special_tokens=False).ids).tobytes()
        rule = FAST_BYTE_RULE if usual(text) else BYTE_RULE
        return b"".join(map(self.codes.__getitem__, rule.findall(text)))

    def encode_each(self, texts: Iterable[str]) -> Iterator[bytes]:
        """encode() of each text, in order; the distinct pieces of a chunk of texts are merged together."""
        chunk, n = [], 0
        for text in texts:
            if chunk and n + len(text) > CHUNK_CHARS:
                yield from self._encode_chunk(chunk)
                chunk, n = [], 0
            chunk.append(text)
            n += len(text)
        if chunk:
            yield from self._encode_chunk(chunk)

    def _encode_chunk(self, texts: list[str]) -> list[bytes]:
        plain = [self.rounds.fits and not any(x in t for x in self.added) and usual(t) for t in texts]
        if not any(plain):
            return [self.encode(t) for t in texts]
        data, at, cuts = piece_starts([t for t, p in zip(texts, plain, strict=True) if p])
        pieces = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(at), [None, pa.py_buffer(np.append(at, len(data))), pa.py_buffer(data)]).dictionary_encode()
        known = pieces.dictionary
        offsets = np.frombuffer(known.buffers()[1], np.int64, len(known) + 1)
        chars, sizes = np.frombuffer(known.buffers()[2], np.uint8, offsets[-1]), np.diff(offsets)
        short = sizes <= LONG_PIECE
        begin, many = np.zeros(len(known), np.int64), np.zeros(len(known), np.int64)
        ids, begin[short], many[short] = self.rounds.ids(chars[np.repeat(short, sizes)], sizes[short])
        raw, far = memoryview(known.buffers()[2]), np.flatnonzero(~short)
        own = [self.codes[str(raw[a:b], "utf-8")] for a, b in zip(offsets[far].tolist(), offsets[far + 1].tolist(), strict=True)]
        many[far] = np.array([len(x) // 4 for x in own], np.int64)
        begin[far] = len(ids) + np.cumsum(many[far]) - many[far]
        ids = np.concatenate((ids.astype("<u4"), np.frombuffer(b"".join(own), "<u4")))
        which = pieces.indices.to_numpy()
        counts = many[which]
        counts[cuts] = 0
        ends = np.cumsum(counts)
        places = np.repeat(begin[which] - (ends - counts), counts)
        places += np.arange(len(places))
        found = ids[places].tobytes()
        ends = (4 * ends[cuts]).tolist()
        got = (found[a:b] for a, b in zip([0, *ends], ends, strict=False))
        return [next(got) if p else self.encode(t) for t, p in zip(texts, plain, strict=True)]


def worker_cache(key, make, version=None, _made: dict = {}):  # noqa: B006  one per Python worker
    """What make() gave for the key in this worker; another version takes its place, so that workers of a long session don't fill up."""
    if key not in _made or _made[key][0] != version:
        _made.pop(key, None)
        _made[key] = version, make()
    return _made[key][1]

