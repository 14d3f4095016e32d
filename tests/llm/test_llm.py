"""The corpus operators against brute force, round trips and held-out accuracy, on small fixtures with the awkward rows."""

import hashlib
import json
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

llm = pytest.importorskip("modspark.llm")

import public_tokenizers as P  # noqa: E402
from tokenizers import Tokenizer  # noqa: E402

from modspark.llm import bpe, common, fingerprints, jaccard, line_templates, mixing, pii, planes, quality, secrets, tiff, tokens  # noqa: E402
from modspark.llm.components import components  # noqa: E402

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
BIG = (1 << 60) + 1  # an id that a float can't hold


def rows_of(texts, sources=None):
    return [(i, t, "en", (sources or ["s0", "s1"])[i % len(sources or "ab")], len(t or "")) for i, t in enumerate(texts)]


@pytest.fixture(scope="session")
def awkward(spark):
    """Nulls in every column, empty and very long texts, ties, repeated rows, a large id."""
    r = random.Random(3)
    word = lambda: "".join(r.choice("abcdefghij") for _ in range(r.randint(2, 7)))
    base = " ".join(word() for _ in range(60))
    texts = ["", None, "one", "two words", base, base, base.upper(), base.replace(" ", "\t"), base + " tail", "x" * 40_000, " ".join(word() for _ in range(9000)), "é ü 日本語 🎉 <|endoftext|> a", "\n\n", " lead and trail "]
    texts += [" ".join(w if r.random() > 0.03 else word() for w in base.split()) for _ in range(12)]
    data = rows_of(texts)
    data += [(None, "no id", None, None, None), (None, None, None, None, None), data[4], data[4], (BIG, "big id +1 (826) 555-4081 190.137.223.204", "en", None, 3)]
    return spark.createDataFrame(data, SCHEMA).repartition(3).cache()


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def collected(df):
    return [r.asDict() for r in df.collect()]


# --- 1 ---


def brute_secrets(t):
    out = []
    for m in re.finditer(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", t, re.I | re.A):
        if len(m[2]) >= 6:
            out.append((m.start(), 0, m.end()))
    out += [(m.start(), 1, m.end()) for m in re.finditer("AKIA[A-Z0-9]+", t) if len(m[0]) >= 20]
    out += [(m.start(), 2, m.end()) for m in re.finditer("[0-9a-f]+", t) if len(m[0]) >= 24]
    return sorted(out)


def test_secret_spans():
    r = random.Random(1)
    bits = ["token", "TOKEN = ", 'api_key":"', "AKIA", "ABCD1234EFGH5678", "deadbeef" * 3, "0123456789abcdef", " ", "=", ":", "secret", "x9.z-", "password : '", "é"]
    for _ in range(4000):
        t = "".join(r.choice(bits) for _ in range(r.randint(0, 9)))
        assert [(s, k, e) for s, k, e, *_ in secrets.base_spans(t)] == brute_secrets(t)


def test_secret_ownership(spark, awkward, empty):
    live, shared = "token = 9f8e7d6c5b4a39281706f5e4d3c2b1a0", "token = 00112233445566778899aabbccddeeff"
    docs = spark.createDataFrame([(1, f"é {live}", "a"), (2, shared, "a"), (3, shared, "b"), (4, f"{shared} {shared}", "c"), (5, None, None), (6, live[:20], None)], "doc_id long, text string, source string")
    got = {r["doc_id"]: r for r in collected(secrets.detect(docs))}
    assert (got[1]["n_live"], got[1]["n_example"]) == (1, 0) and (got[3]["n_live"], got[3]["n_example"]) == (0, 1) and got[4]["n_example"] == 2
    assert got[1]["spans"].split(",")[0].startswith("assign:2:") and "live:10:42" in got[1]["spans"]
    freq = {r["n_owners"]: r["n_repos"] for r in secrets.ownership(secrets.scan(docs)).collect()}
    assert freq[3] == 3 and freq[1] == 1
    assert secrets.detect(empty).count() == 0
    assert secrets.detect(awkward).count() == awkward.count()
    clash = docs.withColumnRenamed("text", "t").withColumn("h", F.lit(1)).withColumn("owner", F.lit(2)).withColumn("row", F.lit(3))
    assert secrets.detect(clash, text_col="t").count() == 6


def brute_ownership(rows):
    """rows (id, text, owner): the whole spans string of each row, by plain loops."""
    held = []
    for _, t, _o in rows:
        t = t or ""
        base = brute_secrets(t)
        values = []
        for m in re.finditer(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", t, re.I | re.A):
            values += [m.span(2)] if len(m[2]) >= 6 else []
        values += [(s, e) for s, k, e in base if k]
        one = [v for v in set(values) if not any(w != v and w[0] < v[1] and v[0] < w[1] and (w[0], -w[1]) < (v[0], -v[1]) for w in values)]
        one += [m.span() for m in re.finditer("[A-Za-z0-9+/_=-]{20,}", t) if re.search("[0-9]", m[0]) and re.search("[A-Za-z]", m[0]) and not any(m.start() < e and s < m.end() for s, e in values)]
        held.append((t, base, one))
    owners, repos = defaultdict(set), defaultdict(set)
    for (_, _, o), (t, _, one) in zip(rows, held, strict=True):
        for s, e in one:
            owners[t[s:e]].add(o)
            repos[t[s:e]].add((o, t))
    out = []
    for (i, _, _), (t, base, one) in zip(rows, held, strict=True):
        spans = list(base)
        for s, e in one:
            n = len(owners[t[s:e]])
            spans.append((s, 4 if n >= 3 else 3 if n == 1 and secrets.entropy(t[s:e]) >= 2.8 else 5, e))
        names = ("assign", "access", "hex", "live", "example", "unsure")
        out.append((i, ",".join(f"{names[k]}:{s}:{e}" for s, k, e in sorted(spans)), max([len(repos[t[s:e]]) for s, e in one], default=0)))
    return out


def test_secret_rows_against_brute_force(spark):
    r = random.Random(8)
    keys = ["".join(r.choice("0123456789abcdef") for _ in range(r.choice((24, 32, 40)))) for _ in range(12)] + ["AKIA" + "".join(r.choice("ABCDEFGH2345") for _ in range(16)) for _ in range(4)]
    keys += ["".join(r.choice("abcXYZ019+/") for _ in range(26)) for _ in range(6)] + ["aaaaaaaaaaaaaaaaaaaaaaa1"]
    put = ["token = ", "password: '", "", "api_key=", "x ", "secret="]
    rows = []
    for i in range(160):
        t = " ".join(r.choice(put) + r.choice(keys[: r.choice((2, 23))]) + r.choice(("", "==", "' ", ".tail", "\n")) for _ in range(r.randint(0, 4)))
        rows.append((i, t or None, r.choice(("a", "b", "c", "d", None))))
    rows += rows[:5]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(4)
    assert Counter((x["doc_id"], x["spans"], x["most_repos"]) for x in secrets.detect(docs).collect()) == Counter(brute_ownership(rows))


def test_secrets_lose_no_candidate(spark):
    key, two, flat = "token = 9f8e7d6c5b4a39281706f5e4d3c2b1a0", "token = 00112233445566778899aabbccddeeff", "password = aaaaaaaa"
    rows = [(i, f"file {i} {key}", "a") for i in range(5)] + [(5, "file 0 " + key, "a"), (6, two, "a"), (7, two, "b"), (8, flat, "c")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = {r["doc_id"]: r for r in collected(secrets.detect(docs))}
    assert all(got[i]["n_live"] == 1 for i in range(6))
    assert all(got[i]["n_live"] == got[i]["n_example"] == 0 and got[i]["n_unsure"] == 1 and "unsure:" in got[i]["spans"] for i in (6, 7, 8))
    assert sorted((r["n_owners"], r["n_repos"]) for r in secrets.ownership(secrets.scan(docs)).collect()) == [(1, 1), (1, 5), (2, 2)]


# --- 2 ---


def brute_classes(rows):
    """Reference: every pair of distinct texts."""
    sets = []
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))
        sets.append((i, {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()))
    root = list(range(len(sets)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(sets)):
        for b in range(a):
            s, t = sets[a][1], sets[b][1]
            if s and t and 100 * len(s & t) >= 75 * len(s | t):
                root[find(a)] = find(b)
    least = defaultdict(list)
    for k, (i, _) in enumerate(sets):
        if i is not None:
            least[find(k)].append(i)
    return sorted(((i, len(s), min(least[find(k)]) if least[find(k)] else None) for k, (i, s) in enumerate(sets)), key=repr)


def near_copies(seed, groups=6, size=14):
    r = random.Random(seed)
    word = lambda: "".join(r.choice("abcdefghijklm") for _ in range(r.randint(2, 6)))
    passage = " ".join(word() for _ in range(30))
    out = []
    for _ in range(groups):
        base = [word() for _ in range(r.randint(6, 150))]
        for _ in range(size):
            out.append(" ".join(w if r.random() > r.choice((0.0, 0.005, 0.01, 0.03)) else word() for w in base) + (" " + passage if r.random() < 0.3 else ""))
    return out


@pytest.mark.parametrize("seed", [1, 2])
def test_links_against_brute_force(spark, seed):
    rows = rows_of(near_copies(seed))
    got = jaccard.link_classes(spark.createDataFrame(rows, SCHEMA).repartition(5))
    assert sorted(((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got.collect()), key=repr) == brute_classes([(r[0], r[1]) for r in rows])


@pytest.mark.parametrize(("hot", "list_nodes"), [(2, 4), (4, 1024), (1 << 30, 3)])
def test_links_with_hot_shingles_and_long_lists(spark, hot, list_nodes):
    """Common shingles sent past their buckets, lists in blocks, pairs handed out early: the same classes."""
    rows = rows_of(near_copies(7, 5, 30))
    rows += [(1000 + i, r[1], "en", "s", 1) for i, r in enumerate(rows[::7])]
    for star_rounds in (0, 2):
        got = jaccard.link_classes(spark.createDataFrame(rows, SCHEMA).repartition(6), star_rounds, list_nodes=list_nodes, hot=hot, held=50)
        assert sorted(((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got.collect()), key=repr) == brute_classes([(r[0], r[1]) for r in rows])


def test_links_of_a_very_long_text(spark):
    words = [np.base_repr(i, 36) for i in range(1_200_000)]
    long_ = " ".join(words)
    rows = rows_of([long_, long_ + " tail", "a short one", " ".join(words[:1_000_000])])
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard.link_classes(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert got == {0: (1_199_996, 0), 1: (1_199_997, 0), 2: (1, 2), 3: (999_996, 0)}


def test_links_of_awkward_rows(awkward, empty):
    rows = [(r["doc_id"], r["text"]) for r in awkward.collect()]
    got = jaccard.link_classes(awkward)
    assert sorted(((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got.collect()), key=repr) == brute_classes(rows)
    assert jaccard.link_classes(empty).count() == 0
    clash = awkward.withColumn("_n", F.lit(5)).withColumn("_stays", F.lit(6)).withColumn("n", F.lit(7)).withColumn("stays", F.lit(8)).withColumn("digest", F.lit(9)).withColumn("bucket", F.lit(1))
    assert jaccard.one_of_each_class(clash).columns == clash.columns and {tuple(r) for r in jaccard.one_of_each_class(clash).select("_n", "_stays", "n", "stays").collect()} == {(5, 6, 7, 8)}
    kept = jaccard.one_of_each_class(awkward)
    assert kept.where("doc_id is null").count() == 2 and kept.where("doc_id is not null").select("doc_id").distinct().count() == kept.where("doc_id is not null").count()


def test_prefix_levels():
    level, reach = jaccard.choose_level(100, 100, np.zeros(100, np.uint8) + 200)
    assert level > 1 and reach >= 100 - 75 + level - 1
    assert jaccard.choose_level(1, 1, np.array([16], np.uint8)) == (1, 1)
    r = random.Random(1)
    for _ in range(300):  # two linked sets share at least L of their first n - t + L members, in any common order
        n = r.randint(4, 60)
        a = set(range(n))
        b = set(r.sample(range(n), r.randint(max(1, int(n * 0.8)), n))) | set(range(1000, 1000 + r.randint(0, 3)))
        if not jaccard.enough(len(a & b), len(a), len(b)):
            continue
        order = {x: r.random() for x in a | b}
        for level in (1, 2, 3):
            pre = [sorted(s, key=order.get)[: len(s) - -(-3 * len(s) // 4) + level] for s in (a, b)]
            assert len(set(pre[0]) & set(pre[1])) >= min(level, len(a & b))


def test_components(spark):
    r = random.Random(2)
    e = [(r.randrange(60), r.randrange(60)) for _ in range(45)]
    root = {}
    find = lambda x: x if root.setdefault(x, x) == x else find(root[x])
    for a, b in e:
        if a != b:
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    got = {x["node"]: x["root"] for x in components(spark.createDataFrame(e, "u long, v long")).collect()}
    assert all(got.get(v, v) == find(v) for v in root)


# --- 3 ---


def test_fingerprints(spark, awkward, empty):
    r = random.Random(1)
    a = " ".join("".join(r.choice("abcdefgh") for _ in range(6)) for _ in range(400))
    b = a[:1400] + "CHANGED" + a[1400:]
    far = " ".join("".join(r.choice("ijklmnop") for _ in range(6)) for _ in range(400))
    f = fingerprints.fingerprint
    assert f(a) == f(a) and fingerprints.likeness(f(a), f(b)) > 0.8 > 0.2 > fingerprints.likeness(f(a), f(far))
    assert max(len(x) for x in f("ab" * 50_000).split(":")) <= 64 and f("") == "4::"
    for x, y in (("kitten", "sitting"), ("", "abc"), ("abc", "abc"), ("aXbXc", "abc")):
        d = [[i + j if not i * j else 0 for j in range(len(y) + 1)] for i in range(len(x) + 1)]
        for i in range(1, len(x) + 1):
            for j in range(1, len(y) + 1):
                d[i][j] = d[i - 1][j - 1] if x[i - 1] == y[j - 1] else 1 + min(d[i - 1][j], d[i][j - 1])
        assert fingerprints.edit_distance(x, y) == d[-1][-1]
    rows = sorted(((x["doc_id"], x["text"] or "") for x in awkward.where("doc_id is not null").collect()), key=lambda x: (x[0], x[1]))
    want = Counter((i, hashlib.sha256(fingerprints.edited(t, rows[(k + 1) % len(rows)][1]).encode()).hexdigest(), f(t)) for k, (i, t) in enumerate(rows))
    got = fingerprints.against_next(awkward.where("doc_id is not null"))
    assert Counter((x["doc_id"], x["edited_sha256"], x["fingerprint"]) for x in got.collect()) == want
    assert fingerprints.against_next(awkward).count() == awkward.count() and fingerprints.against_next(empty).count() == 0
    assert fingerprints.against_next(spark.createDataFrame(rows_of(["only one"]), SCHEMA)).first()["near_next"] == 1.0
    assert fingerprints.fingerprints(awkward.withColumn("fingerprint", F.lit(0))).columns[-1] == "fingerprint"


# --- 4 ---


@pytest.mark.parametrize("how", [tiff.PLAIN, tiff.PACKBITS, tiff.LZW, tiff.DEFLATE])
@pytest.mark.parametrize("predictor", [1, 2])
@pytest.mark.parametrize("tile", [None, (16, 32)])
@pytest.mark.parametrize("order", ["<", ">"])
def test_tiff_roundtrip(how, predictor, tile, order):
    r = random.Random(how + predictor)
    for n in (1, 7, 70, 200):
        data = bytes(r.choice(b"aaab\0\xff") for _ in range(64 * n))
        got = list(tiff.read(tiff.write(data, how, predictor, tile, order, page_rows=50, strip_rows=16)))
        assert b"".join(x[5] for x in got) == data and len(got) == -(-n // 50) and all(x[6] is None for x in got)


def test_tiff_codecs():
    assert tiff.unpack_bits(bytes.fromhex("FEAA0280002AFDAA0380002A22F7AA")) == bytes.fromhex("AAAAAA80002AAAAAAAAA80002A22AAAAAAAAAAAAAAAAAAAA")
    r = random.Random(4)
    for n in (0, 1, 2, 300, 20_000):
        data = bytes(r.randrange(256) for _ in range(n))
        assert tiff.unpack_lzw(tiff.pack_lzw(data)) == data and tiff.unpack_bits(tiff.pack_bits(data)) == data
    assert tiff.unpack_lzw(tiff.pack_lzw(b"ab" * 9000)) == b"ab" * 9000


def test_tiff_broken():
    good = tiff.write(b"x" * 128)
    assert next(iter(tiff.read(b"no image")))[6] and next(iter(tiff.read(b"")))[6] and list(tiff.read(None)) == []
    assert all(any(x[6] for x in tiff.read(good[:k])) for k in (9, len(good) // 2, len(good) - 8))
    loop = bytearray(good)
    at = int.from_bytes(good[4:8], "little")
    n = int.from_bytes(good[at : at + 2], "little")
    loop[at + 2 + 12 * n : at + 6 + 12 * n] = good[4:8]
    assert "loop" in list(tiff.read(bytes(loop)))[-1][6]


def made_tiff(blocks, **tags):
    """A little-endian file of one directory with these tags (by the module's names) over the given blocks."""
    import struct

    out, places = bytearray(b"II*\0\0\0\0\0"), []
    for b in blocks:
        places.append(len(out))
        out += b
    values = {getattr(tiff, k): v if isinstance(v, list) else [v] for k, v in tags.items()}
    key, size = (tiff.TILE_OFFSETS, tiff.TILE_COUNTS) if tiff.TILE_WIDTH in values else (tiff.STRIP_OFFSETS, tiff.STRIP_COUNTS)
    values |= {key: places, size: [len(b) for b in blocks]}
    body = b""
    for tag, v in sorted(values.items()):
        at = len(out)
        if len(v) > 1:
            out += struct.pack(f"<{len(v)}I", *v)
        body += struct.pack("<HHII", tag, 4, len(v), at if len(v) > 1 else v[0])
    struct.pack_into("<I", out, 4, len(out))
    return bytes(out + struct.pack("<H", len(values)) + body + struct.pack("<I", 0))


def test_tiff_samples_of_other_widths():
    got = next(tiff.read(made_tiff([bytes([0b10110000, 0b01000000]), bytes([0b11100000])], WIDTH=3, HEIGHT=3, BITS=1, ROWS_PER_STRIP=2)))
    assert got[6] is None and list(got[5]) == [1, 0, 1, 0, 1, 0, 1, 1, 1]
    got = next(tiff.read(made_tiff([bytes([0x1F, 0xA0])], WIDTH=3, HEIGHT=1, BITS=4)))
    assert list(got[5]) == [1, 15, 10]
    got = next(tiff.read(made_tiff([bytes([1, 2]), bytes([3, 4]), bytes([5, 6])], WIDTH=2, HEIGHT=1, BITS=[8, 8, 8], SAMPLES=3, PLANAR=2)))
    assert list(got[5]) == [1, 3, 5, 2, 4, 6]
    got = next(tiff.read(made_tiff([zlib.compress(bytes([1, 0, 1, 0]))], WIDTH=2, HEIGHT=1, BITS=16, COMPRESSION=tiff.DEFLATE, PREDICTOR=2)))
    assert np.frombuffer(got[5], "<u2").tolist() == [1, 2]


@pytest.mark.parametrize("tags", [{"ROWS_PER_STRIP": 0}, {"WIDTH": 0}, {"HEIGHT": 0}, {"SAMPLES": 0}, {"WIDTH": 0xFFFFFFFF, "HEIGHT": 0xFFFFFFFF}, {"WIDTH": 70_000, "HEIGHT": 70_000, "COMPRESSION": 8},
    {"TILE_WIDTH": 0, "TILE_HEIGHT": 16}, {"TILE_WIDTH": 1 << 31, "TILE_HEIGHT": 1 << 31, "COMPRESSION": 5}, {"BITS": 7}, {"PREDICTOR": 3}, {"COMPRESSION": 99}, {"SAMPLES": 1 << 30}, {"HEIGHT": 1 << 20}])
def test_tiff_hostile_tags(tags):
    rows = list(tiff.read(made_tiff([b"x" * 64], **({"WIDTH": 8, "HEIGHT": 8, "BITS": 8} | tags))))
    assert len(rows) == 1 and rows[0][6] and rows[0][5] is None


def test_tiff_fuzzed():
    r, good = random.Random(3), [tiff.write(bytes(range(64)) * 6, how, p, t, o) for how, p, t, o in tiff.VARIETY]
    for _ in range(3000):
        data = bytearray(r.choice(good))
        for _ in range(r.randint(1, 4)):
            data[r.randrange(len(data))] = r.choice((0, 1, 255, r.randrange(256)))
        for row in tiff.read(bytes(data)):
            assert (row[5] is None) == (row[6] is not None)


def test_tiff_varied_runs_every_decoder(spark):
    used = {zlib.crc32(raw + b"\0" * (-len(raw) % 64 or (0 if raw else 64))) % len(tiff.VARIETY) for (raw,) in ((r["text"].encode(),) for r in common.documents(spark, "/root/testdata/sf0.01").select("text").collect())}
    assert used == set(range(len(tiff.VARIETY)))
    kept = spark.createDataFrame([(1, "a", tiff.varied(b"x" * 64))], "page int, error string, media binary")
    got = tiff.pages(kept, "media", ("page", "error", "media")).first().asDict()
    assert got["page"] == 1 and got["error"] == "a" and got["page_"] == 0 and got["error_"] is None and bytes(got["samples"]) == b"x" * 64


def test_tiff_query(awkward, empty, spark, sf):
    got = tiff.pages(tiff.store(awkward), "media", ("doc_id", "gone", "n_bytes"))
    assert got.where("error is not null").count() == 0
    back = defaultdict(bytes)
    for r in got.where("n_bytes = 40000").orderBy("page").collect():
        back[r["doc_id"]] += bytes(r["samples"])
    assert next(iter(back.values()))[:40_000] == b"x" * 40_000
    assert tiff.pages(tiff.store(empty), "media").count() == 0
    told = {r["doc_id"]: r for r in collected(tiff.op4_tiff_pages(spark, sf))}
    for r in common.documents(spark, sf).collect():
        raw = r["text"].encode()
        raw += b"\0" * (-len(raw) % 64 or (0 if raw else 64))
        x = told[r["doc_id"]]
        assert (x["payload_bytes"], x["payload_sha256"], x["tail_crc32"]) == (len(raw), hashlib.sha256(raw).hexdigest(), zlib.crc32(raw[-64:]))


# --- 5 ---


def test_targets():
    t = mixing.target_sizes({"a": 100, "b": 100, None: 100})
    assert t == {"a": 187.5, "b": 75.0, None: 37.5}
    t = mixing.target_sizes({"a": 10, "b": 1000, "c": 5})
    assert t["a"] == 30 and t["c"] == 15 and abs(sum(t.values()) - 1015) < 1e-9
    assert mixing.target_sizes({}) == {} and mixing.target_sizes({"a": 0}) == {"a": 0.0}


def test_round_pair_keeps_mass_and_expectation():
    r = random.Random(1)
    for _ in range(300):
        p, q, a, b = r.random() * 0.98 + 0.01, r.random() * 0.98 + 0.01, r.randint(1, 50), r.randint(1, 50)
        mean = [0.0, 0.0]
        for k in range(200):
            x, y = mixing.round_pair(p, a, q, b, (k + 0.5) / 200)
            assert abs(x * a + y * b - p * a - q * b) < 1e-6 and min(x, y) > -1e-9 and max(x, y) < 1 + 1e-9 and min(x, 1 - x, y, 1 - y) < 1e-9
            mean = [mean[0] + x / 200, mean[1] + y / 200]
        assert abs(mean[0] - p) < 0.02 and abs(mean[1] - q) < 0.02


def test_mix(spark, awkward, empty):
    r = random.Random(1)
    rows = rows_of([" ".join("w" * r.randint(1, 3) for _ in range(r.randint(0, 40))) for _ in range(600)], ["a", "b", "c", None])
    df = spark.createDataFrame(rows, SCHEMA)
    got = collected(mixing.mix(df))
    by = defaultdict(lambda: [0, 0.0, 0])
    for x in got:
        by[x["source"]][0] += x["size"]
        by[x["source"]][1], by[x["source"]][2] = x["target"], by[x["source"]][2] + x["taken"]
        assert x["taken"] <= 3 * x["size"] and (x["size"] == 0 or x["taken"] % x["size"] == 0)
    assert all(abs(t - s) <= 40 for _, t, s in by.values()) and len(got) == 600
    again = {x["doc_id"]: x["taken"] for x in collected(mixing.mix(df.repartition(7)))}
    assert again == {x["doc_id"]: x["taken"] for x in got}
    assert mixing.mix(empty).count() == 0 and mixing.mix(awkward).count() == awkward.count()
    sizes = {r["doc_id"]: r["size"] for r in awkward.where("doc_id is not null").select("doc_id", mixing.word_count().alias("size")).collect()}
    assert sizes == {r["doc_id"]: len(re.findall(r"[^\x20\x09-\x0D]+", r["text"] or "")) for r in awkward.where("doc_id is not null").collect()}
    clash = df.withColumn("_n", F.lit(77)).withColumn("_times", F.lit(1)).withColumn("times", F.lit(2)).withColumn("print", F.lit(3)).withColumn("number", F.lit(4)).withColumn("key", F.lit(5))
    assert {tuple(x) for x in mixing.repeat(clash).select("_n", "_times", "times", "print", "number", "key").collect()} == {(77, 1, 2, 3, 4, 5)}
    many = collected(mixing.mix(spark.createDataFrame([(1, "a b c", "en", "s", 5)] * 50 + [(2, "a b c d", "en", "t", 7)] * 50, SCHEMA)))
    assert len(many) == 100 and {x["source"]: sum(y["size"] for y in many if y["source"] == x["source"]) for x in many} == {"s": 150, "t": 200}
    copies = mixing.repeat(df)
    assert copies.select(F.sum(mixing.word_count())).first()[0] == sum(x["taken"] for x in got) and copies.columns == df.columns


# --- 6 ---


def brute_pii(text):
    out = [(m.start(), 0, m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)]
    out += [(m.start(), 1, m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(x) <= 255 for x in m[0].split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
        d = pii.digits_of(m[0])
        if 12 <= len(d) <= 19 and pii.luhn(d):
            out.append((m.start(), 2, m.end()))
    out += [(m.start(), 3, m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text) if 9 <= len(pii.digits_of(m[0])) <= 15]
    return sorted(out)


def test_pii_base_spans():
    r = random.Random(5)
    for _ in range(6000):
        t = "".join(r.choice("a1.@+- (0%b4") for _ in range(r.randint(0, 34)))
        assert brute_pii(t) == pii.base_spans(t)


def test_pii_field():
    w = pii.fitted()
    r, right, true, found = random.Random(99), 0, 0, 0
    for _ in range(200):
        text, spans = pii._sample(r)
        got = {(s, e, k) for s, k, e in pii.field_spans(text, w)}
        right, true, found = right + len(got & set(spans)), true + len(spans), found + len(got)
    assert right / true > 0.93 and right / found > 0.95
    base, spans = pii.all_spans("call +1 (826) 555-4081 190.137.223.204 now", w)
    assert [x[1] for x in base] == [1] and [x[1] for x in spans] == [3, 1]
    assert pii.all_spans("nothing here, version 2.0. or 2024-01-01 12:30", w)[1] == []


def test_pii_field_adds_every_kind():
    """Planted spans of a seed that the weights were not fitted on: by kind, what the patterns find and what is found in all."""
    w, r = pii.fitted(), random.Random(123)
    true, base, every = Counter(), Counter(), Counter()
    for _ in range(400):
        text, spans = pii._sample(r)
        b, a = pii.all_spans(text, w)
        for s, e, k in spans:
            true[k], base[k], every[k] = true[k] + 1, base[k] + ((s, k, e) in b), every[k] + ((s, k, e) in a)
    for k in range(4):
        assert base[k] / true[k] < 0.75 and every[k] / true[k] > (0.85, 0.95)[k != 3], pii.KINDS[k]
    for text, kind in (("mail jo (at) site (dot) org now", 0), ("jo @ site.org 1", 0), ("host 10[.]1[.]2[.]3 up", 1), ("host fe80::1ff:fe23:4567 up 1", 1), ("(826) 555-4081 was called", 3)):
        b, a = pii.all_spans(text, w)
        assert not b and [k for _, k, _ in a] == [kind], text


@pytest.mark.parametrize("text", ["a" * 1_000_000 + "1", "a" * 1_000_000 + " 1", "1" + "b" * 1_000_000 + "@", "a." * 400_000 + "@b", "a@" * 200_000, "a@b." * 60_000, "\xa0" * 300_000 + "1", "+1 " * 100_000, "(at) " * 60_000])
def test_pii_long_runs(text):
    import time

    w, t = pii.fitted(), time.monotonic()
    pii.all_spans(text, w)
    assert time.monotonic() - t < 4


def test_pii_added_spans_touch_no_base_span_of_their_kind():
    w, r = pii.fitted(), random.Random(6)
    for _ in range(400):
        text = " ".join(pii._sample(r)[0] for _ in range(2))
        base = pii.base_spans(text)
        want = [(s, k, e) for s, k, e in pii.field_spans(text, w) if not any(k == kk and s < b and a < e for a, kk, b in base)]
        assert pii.all_spans(text, w)[1] == sorted(base + want)


def test_pii_segmentation_against_all_segmentations():
    w = pii.fitted()
    r = random.Random(4)
    for _ in range(40):
        text, _ = pii._sample(r)
        for window in pii.windows(text):
            bounds, segs = pii.candidates(text, *window)
            n = len(bounds) - 1
            if n > 14 or len(segs) > 12:
                continue
            value = lambda choice: sum(float(w[k] @ f) for _, _, k, f in choice)
            every = [[]]
            for s in segs:
                every += [c + [s] for c in every if all(s[1] <= o[0] or o[1] <= s[0] for o in c)]
            got = {(i, j, k) for i, j, k in pii.best_segments(n, segs, w)}
            assert abs(value([s for s in segs if s[:3] in got]) - max(map(value, every))) < 1e-9
            z, p = pii.expectations(n, segs, w)
            total = np.logaddexp.reduce([value(c) for c in every])
            assert abs(z - total) < 1e-6 and all(abs(p[i] - sum(np.exp(value(c) - total) for c in every if any(x is s for x in c))) < 1e-6 for i, s in enumerate(segs))


def test_pii_rows(awkward, empty):
    got = collected(pii.detect(awkward))
    assert len(got) == awkward.count() and {r["doc_id"] for r in got} >= {BIG, None}
    assert next(r for r in got if r["doc_id"] == BIG)["n_added"] == 1
    assert pii.detect(empty).count() == 0


# --- 7, 10 ---

ODD = ["", "  a  b　c", "it's I'LL don't", "<|endoftext|> x<|startoftext|>", "İstanbul ß ŉ", "日本語 テスト１２３", "áé ê̂", "²½¾ ª µ", "\x85x\xa0y\xadz\x1c", "ΑΣ Σ", "tab\t\tnew\n\n l \r\n", "٣٤", "x" * 5000, "🎉🎊", "K Å ﬁ", "\x00\x01 a", "a\x1cb c\x1f d", "\x7f \x0b\x0c x\x08y", "'s 'T ſ'ſ", "a  b   c "]


@pytest.mark.parametrize(("name", "coder"), [("word_bpe_49k.json", tokens.LexiconCoder), ("byte_bpe_50k.json", tokens.ByteCoder)])
def test_tokens_equal_the_library(name, coder, spark, sf):
    lib, c = Tokenizer.from_file(P.path(name)), coder(P.path(name))
    r = random.Random(1)
    texts = ODD + [x["text"] for x in common.documents(spark, sf).limit(40).collect()] + ["".join(r.choice("abé'sS 12\t日.") for _ in range(40)) for _ in range(300)]
    for t in texts:
        ids, got = lib.encode(t, add_special_tokens=False).ids, c.encode(t)
        raw = got[0] if isinstance(got, tuple) else got
        assert raw == np.array(ids, "<u4").tobytes(), t[:50]
        if isinstance(got, tuple):
            assert got[1] == lib.decode(ids, skip_special_tokens=False), t[:50]


def test_scripts_go_through_the_lexicon():
    """Curly quotes, dashes, other scripts and added tokens: equal to the library, and none of it left to the library whole."""
    name = P.path("word_bpe_49k.json")
    lib, r = Tokenizer.from_file(name), random.Random(5)
    plain = ["don\u2019t \u2014 she said \u201cno\u201d", "Привет, МИР №5", "Ωραία ΑΣ ΣΑΣ", "中文 テスト １２３", "नमस्ते दुनिया", "ﬁne ﬂow ½ Ⅷ ①", "a\u2028b\u00a0c\u3000d\u200be", "İ ı ſ K Å e\u0301", "🎉👩\u200d👩\u200d👧 ok", "<|startoftext|>Hi\u2026<|endoftext|><|endoftext|> x <|endoftext", "\u1c89\U0001e5d0 new letters"]
    signs = [chr(c) for c in range(32, 0x3000, 7)] + list("\u2019\u201c\u2014 aA1\n") * 60 + ["<|endoftext|>"] * 9
    texts = plain + ["".join(r.choice(signs) for _ in range(30)) for _ in range(1500)]
    coder = tokens.LexiconCoder(name)
    words = Counter(w for t in texts for w in coder.words(t))
    lex = {w: coder.merged_ids(w) for w in list(words)[::2]}
    coder.lexicon = tokens.Lexicon.mapped(tokens.pack_lexicon(lex))
    left = []
    whole = coder.library
    class Counted:
        normalizer = whole.normalizer

        def encode(self, t, **how):
            left.append(t)
            return whole.encode(t, **how)

    coder.library = Counted()
    for t in texts:
        ids = lib.encode(t, add_special_tokens=False).ids
        assert coder.encode(t) == (np.array(ids, "<u4").tobytes(), lib.decode(ids, skip_special_tokens=False)), ascii(t)
    assert all(tokens.unassigned().search(t) for t in left) and not any(t in left for t in plain[:-2])
    assert any("\u2019" in w for w in words) and any("\u4e00" < w for w in words)


def test_every_code_point_splits_as_in_the_library():
    split, odd = Tokenizer.from_file(P.path("word_bpe_49k.json")).pre_tokenizer, tokens.unassigned()
    for cp in range(0x80, 0x110000, 3):
        c = chr(cp)
        if 0xD800 <= cp < 0xE000 or odd.search(c):
            continue
        said = [b - a for _, (a, b) in split.pre_tokenize_str(f"a{c}{c}a")]
        assert said == [len(x) for x in tokens.WORD_RULE.findall(f"a{c}{c}a")], hex(cp)


def test_merges_spelled_out():
    c = tokens.LexiconCoder(P.path("word_bpe_49k.json"))
    m = tokens.Merger(P.path("word_bpe_49k.json"))
    r = random.Random(2)
    for _ in range(500):
        w = "".join(r.choice("theandioné1") for _ in range(r.randint(1, 14)))
        assert m.ids("".join(c.signs[b] for b in w.encode())) == c.merged_ids(w)


def test_piece_starts():
    r = random.Random(6)
    signs = "aabcsstmdrevl'''' \n\t\r\xa0.,!?-12" + "".join(c for c in map(chr, range(0x250)) if tokens.usual(c))
    groups = [["".join(r.choice(signs if r.random() < 0.1 else signs[:40]) for _ in range(r.randint(0, 14))) for _ in range(r.randint(1, 4))] for _ in range(4000)]
    for texts in [*groups, [""], ["", ""], [" "], ["a ", " b"], ["x'", "s"], ["'r", "e"], [signs]]:
        data, at, cuts = tokens.piece_starts(texts)
        ends, between = [*at[1:], len(data)], set(cuts.tolist())
        got = [data[a:b].decode() for i, (a, b) in enumerate(zip(at, ends, strict=True)) if i not in between]
        assert got == [x for t in texts for x in tokens.FAST_BYTE_RULE.findall(t)], texts


def test_new_pieces_are_merged_together(monkeypatch):
    """op10's time went into pieces that were merged one by one: of usual texts only very long ones are."""
    path, r = P.path("byte_bpe_50k.json"), random.Random(8)
    lib, c, alone = Tokenizer.from_file(path), tokens.ByteCoder(path), []
    word = lambda: "".join(r.choice(("an", "th", "ing", "ñ", "or", "ón", "x", "aaa", "Er", "7", "--")) for _ in range(r.randint(1, 9)))
    usual = [" ".join(word() for _ in range(300)) for _ in range(30)] + ["", " ", "a" * 64, "ab" * 32 + " " + "=" * 63, "\n" * 50 + "x"]
    merge = c.merge
    c.merge = lambda piece: alone.append(piece) or merge(piece)
    want = lambda t: np.array(lib.encode(t, add_special_tokens=False).ids, "<u4").tobytes()
    assert list(c.encode_each(usual)) == [want(t) for t in usual] and not alone
    longer = ["a" * 65, "é" * 33, "x" * 5000, "".join(r.choice("abcdé") for _ in range(900)) + " b", "a" * 65]
    mixed = [t for pair in zip(usual, (ODD + longer) * 2, strict=False) for t in pair] + longer
    for size in (1, 700, 8 << 20):
        monkeypatch.setattr(tokens, "CHUNK_CHARS", size)
        assert list(c.encode_each(mixed)) == [want(t) for t in mixed]
    assert list(c.encode_each([])) == []


def test_merges_of_another_order(tmp_path):
    """A file in which a part is made after what it is part of: its pieces are left to the library."""
    with open(P.path("byte_bpe_50k.json"), encoding="utf-8") as f:
        told = json.load(f)
    told["model"]["merges"] = told["model"]["merges"][3000:] + told["model"]["merges"][:3000]
    path = str(tmp_path / "other.json")
    with open(path, "w", encoding="utf-8") as f:
        json.dump(told, f)
    lib, c = Tokenizer.from_file(path), tokens.ByteCoder(path)
    texts = ["the other thing was another", "", "¡año! it's"]
    assert not c.rounds.fits
    assert list(c.encode_each(texts)) == [np.array(lib.encode(t, add_special_tokens=False).ids, "<u4").tobytes() for t in texts]


def test_transducer_is_exact_and_minimal():
    r = random.Random(1)
    words = sorted({"".join(r.choice("abc") for _ in range(r.randint(1, 6))) + r.choice(("ing", "ed", "")) for _ in range(400)})
    auto = tokens.Transducer.build([w.encode() for w in words])
    assert [auto.number(w.encode()) for w in words] == list(range(len(words)))
    assert auto.number(b"zzz") == auto.number(b"") == -1 and auto.number(words[0].encode() + b"q") == -1
    rights = set()  # a minimal automaton has one state per distinct set of endings
    for p in {w[:i] for w in words for i in range(len(w) + 1)}:
        rights.add(frozenset(w[len(p) :] for w in words if w.startswith(p)))
    assert len(auto.final) == len(rights)
    lex = tokens.Lexicon.mapped(tokens.pack_lexicon({w: [i, i + 1][: 1 + i % 2] for i, w in enumerate(words)}))
    assert all(lex.ids(w).tolist() == [i, i + 1][: 1 + i % 2] for i, w in enumerate(words)) and lex.ids("no") is None
    assert tokens.Lexicon.mapped(tokens.pack_lexicon({})).ids("a") is None


def test_encode_rows(spark, awkward, empty):
    lib = Tokenizer.from_file(P.path("word_bpe_49k.json"))
    for words in (0, 50):
        for r in bpe.encode(awkward.withColumn("ids", F.lit("clash")), lexicon_words=words).collect():
            ids = lib.encode(r["text"] or "", add_special_tokens=False).ids
            assert r["ids"] == ids and r["decoded"] == lib.decode(ids, skip_special_tokens=False)
    assert bpe.encode_digests(awkward).count() == awkward.count() and bpe.encode_digests(empty).count() == 0 and bpe.encode(empty).count() == 0
    many = bpe.frequent_words(spark.createDataFrame(rows_of(["a b b c c c d"]), SCHEMA), bpe.default_path(), 2)
    assert many == ["b", "c"]


@pytest.mark.parametrize("kind", [planes.BYTE, planes.BIT])
def test_shards(kind):
    r = np.random.default_rng(1)
    for n in (0, 1, 63, 1000):
        ids = r.integers(0, 2**32, n, dtype=np.uint32)
        assert (planes.unshuffle(planes.shuffle(ids, kind), n, kind) == ids).all()
    ids = r.integers(0, 50_257, 1000, dtype=np.uint32)
    s = planes.Shard(planes.write_shard(ids, [5, None, BIG], [300, 0, 700], 64, kind))
    assert s.doc_ids == [5, None, BIG] and (s.read(290, 400) == ids[290:690]).all() and len(s.index) == 16
    with pytest.raises(ValueError):
        planes.Shard(b"broken file, no shard at all")


def test_shard_rows(awkward, empty):
    lib = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    rows = sorted(((r["doc_id"], r["text"] or "") for r in awkward.where("doc_id is not null").collect()), key=lambda x: (x[0], x[1]))
    want, start = [], 0
    for i, t in rows:
        ids = [*lib.encode(t, add_special_tokens=False).ids, 2]
        want.append((i, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        start += len(ids)
    got = planes.read_back(common.keep(planes.shards(awkward.where("doc_id is not null")), "t"))
    assert sorted((r["doc_id"], r["start"], r["n_tokens"], r["ids_crc32"]) for r in got.collect()) == sorted(want)
    assert planes.read_back(common.keep(planes.shards(empty), "t")).count() == 0
    assert planes.read_back(common.keep(planes.shards(awkward), "t")).count() == awkward.count()


# --- 8 ---


def brute_lines(rows, depth=3, min_tokens=3, min_body=8, min_docs=3, long_tokens=50, long_docs=2, said=None):
    """rows: distinct (id, text). Kept text of each; said: a dictionary that gets the templates of each."""
    keys, words = {}, {}
    for i, t in rows:
        for pos, line in enumerate((t or "").split("\n")):
            w = [("<*>" if re.search("[0-9]", x) else x) for x in re.findall(r"[^\x20\x09-\x0D]+", line)]
            n, body = len(w), max(len(w) - depth, 0)
            if n < min_tokens:
                continue
            words[i, t, pos] = w
            at = [depth + body * k // 4 for k in range(5)]
            mine = [(0, *w)]
            if body >= min_body:
                pairs = [(x, y) for x in range(4) for y in range(x + 1, 4)]
                mine += [(k + 1, *[x if p < depth or any(at[q] <= p < at[q + 1] for q in two) else None for p, x in enumerate(w)]) for k, two in enumerate(pairs)]
            elif body >= 3:
                mine += [(k + 1, *[None if p == depth + k else x for p, x in enumerate(w)]) for k in range(body)]
            keys[i, t, pos] = mine
    seen = defaultdict(set)
    for (i, t, _), ks in keys.items():
        for k in ks:
            seen[k].add((i is None, i, t))
    least = lambda k: long_docs if k[0] == 0 and len(k) > long_tokens else min_docs
    many = {k: (len(v), min(v, key=lambda x: (x[0], x[1] or 0))[1]) for k, v in seen.items() if len(v) >= least(k)}
    gone, joined = set(), {}
    for at, ks in keys.items():
        mine = [k for k in ks if k in many]
        if mine:
            joined[at] = max(mine, key=lambda k: (many[k][0], -k[0]))
            gone |= {at} if any(many[k][1] != at[0] for k in mine) else set()
    out, members = {}, defaultdict(list)
    for at, k in joined.items():
        members[k].append(words[at])
    text = {k: " ".join(x[0] if len(set(x)) == 1 else "<*>" for x in zip(*w, strict=True)) for k, w in members.items()}
    for i, t in rows:
        lines = (t or "").split("\n")
        out[i, t] = "\n".join(x for p, x in enumerate(lines) if (i, t, p) not in gone)
        if said is not None:
            said[i, t] = [text[joined[i, t, p]] for p in range(len(lines)) if (i, t, p) in joined]
    return out


def test_line_templates(spark, awkward, empty):
    r = random.Random(1)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(5))
    boiler = [" ".join(word() for _ in range(k)) for k in (2, 3, 6, 14, 60)]
    docs = []
    for i in range(40):
        lines = [" ".join(word() for _ in range(r.randint(1, 15))) for _ in range(4)]
        b = r.choice(boiler).split()
        for _ in range(2):
            p = r.randrange(len(b))
            b[p] = word() if r.random() < 0.3 else b[p]
        docs.append((i, "\n".join([*lines[:2], f"  request {i} took 1{i}ms for user{i}  ", f"connection from host {word()} closed by peer", " ".join(b), r.choice(boiler), *lines[2:]])))
    pair = " ".join(word() for _ in range(55))
    docs += [(100, pair + "\nfirst"), (101, "second\n" + pair), (102, " ".join(pair.split()[:40])), (103, " ".join(pair.split()[:40]))]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = {(x["doc_id"]): x["text"] for x in line_templates.drop_recurring(df).collect()}
    said: dict = {}
    want = brute_lines(docs, said=said)
    assert all(got[i] == want[i, t] for i, t in docs) and any(got[i] != t for i, t in docs)
    assert "request 7" not in got[7] and "request 0" in got[0] and "connection" in got[0] and "connection" not in got[7]
    assert pair in got[100] and got[101] == "second" and got[103] == docs[-1][1]
    assert line_templates.drop_recurring(df, long_docs=3).where("doc_id = 101").first()["text"] == "second\n" + pair
    left = common.keep(line_templates.dropped_lines(df), "t")
    each = left.select("id", F.explode("told").alias("x")).select("id", "x.*")
    text = each.join(line_templates.merged(each), "key").orderBy("id", "pos").collect()
    assert all([x["template"] for x in text if x["id"] == i] == said[i, t] for i, t in docs)
    assert "connection from host <*> closed by peer" in {x["template"] for x in text} and "request <*> took <*> for <*>" in {x["template"] for x in text}
    odd = [(x["doc_id"], x["text"]) for x in awkward.where("doc_id is not null").select("doc_id", "text").distinct().collect()]
    want = brute_lines(odd)
    for x in line_templates.drop_recurring(awkward).where("doc_id is not null").collect():
        assert (x["text"] or "") in {want[i, t] for i, t in odd if i == x["doc_id"]}
    assert line_templates.drop_recurring(awkward).count() == awkward.count() and line_templates.drop_recurring(empty).count() == 0
    clash = df
    for c in ("pos", "key", "row", "keys", "found", "lines", "same", "id", "_gone", "_row", "leaf"):
        clash = clash.withColumn(c, F.lit(7))
    assert line_templates.drop_recurring(clash).columns == clash.columns and line_templates.drop_recurring(clash).where("found <> 7 or lines <> 7").count() == 0


def test_line_templates_stay_in_the_jvm(spark, awkward):
    frames = [line_templates.drop_recurring(awkward), line_templates.line_keys(awkward), line_templates.templates_of(awkward)]
    left = line_templates.dropped_lines(awkward)
    frames += [left, line_templates.merged(left.select(F.explode("told").alias("x")).select("x.*"))]
    said = "".join(f._jdf.queryExecution().toString() for f in frames)
    assert "Python" not in said and "Arrow" not in said and "Pandas" not in said


# --- 9 ---


def test_quality_held_out(spark):
    sf = "/root/testdata/sf0.01"
    got = quality.op9_nb_svm_quality(spark, sf).join(quality.labels_of(spark, sf), "doc_id").where("held_out")
    rows = got.collect()
    good, bad = [r for r in rows if r["quality"] == 1], [r for r in rows if r["quality"] == 0]
    assert len(rows) > 40 and sum(r["predicted"] for r in good) / len(good) > 0.97 and sum(1 - r["predicted"] for r in bad) / len(bad) > 0.7


def test_quality_edges(spark, awkward, empty):
    docs = awkward.select("doc_id", "text")
    one = docs.where("doc_id is not null").select("doc_id", F.lit(1).alias("quality"))
    m = quality.fit(docs, one)
    assert all(0.9 < r["score"] <= 1 for r in quality.with_score(awkward, m).collect())
    none = quality.fit(docs, one.where("quality = 5"))
    assert {round(r["score"], 3) for r in quality.with_score(awkward, none).collect()} == {0.5}
    assert quality.with_score(empty, none).count() == 0
    held = docs.where("doc_id is not null").select("doc_id", quality.held_out().alias("h")).collect()
    assert all(r["h"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) for r in held)


def test_dual_descent_reaches_the_primal_optimum():
    r = np.random.default_rng(1)
    rows = [np.sort(r.choice(40, 6, replace=False)) for _ in range(60)]
    values = [r.normal(size=6) for _ in rows]
    y = r.integers(0, 2, 60)
    w, b = quality.dual_descent(rows, values, y, np.ones(60), rounds=3000)

    def loss(w, b):
        m = np.array([w[i] @ v + b for i, v in zip(rows, values, strict=True)]) * np.where(y == 1, 1, -1)
        return 0.5 * (w @ w + b * b) + (np.maximum(0, 1 - m) ** 2).sum()

    best = loss(w, b)
    for _ in range(300):
        step = np.zeros_like(w)
        step[:40] = r.normal(size=40) * 1e-3
        assert loss(w + step, b + r.normal() * 1e-3) >= best - 1e-6


# --- the pipeline ---


def test_pipeline(spark, sf):
    import corpus_pipeline as p

    docs = common.documents(spark, sf)
    assert [n for n, _ in p.STAGES] == ["quality classifier", "line dedup", "n-gram Jaccard join", "mixing sources to target weights", "BPE encoding and decoding"]
    frames = [docs]
    for _, stage in p.STAGES:
        frames.append(common.keep(stage(spark, frames[-1], sf), "t"))
    raw, good, lines, single, mixed, coded = frames
    assert all(f.columns == docs.columns for f in frames[:-1])
    labels = quality.labels_of(spark, sf)
    kept = good.join(labels, "doc_id").groupBy("quality").count().collect()
    total = dict(raw.join(labels, "doc_id").groupBy("quality").count().collect())
    assert {r["quality"]: r["count"] for r in kept}[1] == total[1] and {r["quality"]: r["count"] for r in kept}.get(0, 0) < total[0]
    want = brute_lines([(r["doc_id"], r["text"]) for r in good.collect()], long_docs=3)
    assert {(r["doc_id"], r["text"]) for r in lines.collect()} == {(i, t) for (i, _), t in want.items()}
    classes = brute_classes([(r["doc_id"], r["text"]) for r in lines.collect()])
    assert sorted(r["doc_id"] for r in single.collect()) == sorted(i for i, _, c in classes if i == c)
    assert Counter(r["doc_id"] for r in mixed.collect()) == Counter({r["doc_id"]: r["taken"] // r["size"] for r in mixing.mix(single).collect() if r["taken"]})
    lib = Tokenizer.from_file(P.path("word_bpe_49k.json"))
    text = {r["doc_id"]: r["text"] for r in mixed.collect()}
    assert coded.count() == mixed.count() and all(r["ids"] == lib.encode(text[r["doc_id"]], add_special_tokens=False).ids for r in coded.limit(30).collect())


def test_oracle_sql_agrees(spark):
    import duckdb

    from modspark.llm.queries import ORACLES, QUERIES

    sf, c = "/root/testdata/sf0.001", duckdb.connect()
    c.execute(f"create view documents as select * from '{sf}/documents.parquet'")
    for name, sql in ORACLES.items():
        got, r = QUERIES[name](spark, sf), c.execute(sql)
        cols = [x[0] for x in r.description]
        assert sorted(map(tuple, got.select(*cols).collect()), key=repr) == sorted(r.fetchall(), key=repr), name


