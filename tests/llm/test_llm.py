"""Operators for training data against brute force, and their defined cases."""

import base64
import hashlib
import json
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from evigraph.llm import (
    blocks, common, components, hashing, op1_transport, op2_language, op3_byte_bpe, op4_probminhash, op5_hilbert, op6_licenses, op7_simple8b, op8_weighted_sampling, op9_fuzzy_lines, op10_mixture, queries,
)

OPS = queries.queries()
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, shard string, hilbert string, n_lines string, media string, score string, size string, finds string"
BASE = "the quick brown fox jumps over the lazy dog and then runs home across the wide green field by the old mill"
ODD = [
    (1, BASE, "en", "b", 100), (1, BASE, "en", "b", 100), (2, BASE, "en", "a", 100), (3, None, "en", "a", 0), (4, "", None, None, 0),
    (5, "a" * 5000, "en", "a", 5000), (6, "  \n\t ", "fr", "b", 4), (7, BASE.replace("quick", "slow") + " today", "fr", "b", 110),
    (8, "ein kleiner text mit ß und ü\nLicensed under the Apache License, Version 2.0.\n" * 3, "de", None, 10), (9, "\U0001f600 ½ \x1c x　y", "fr", "c", 9), (None, "no id here at all", "en", "a", 17),
]


@pytest.fixture(scope="module")
def odd(spark, tmp_path_factory):
    d = str(tmp_path_factory.mktemp("odd"))
    spark.createDataFrame([(*r, *["x"] * 7) for r in ODD], SCHEMA).write.parquet(f"{d}/documents.parquet")
    return d


@pytest.fixture(scope="module")
def empty(spark, tmp_path_factory):
    d = str(tmp_path_factory.mktemp("empty"))
    spark.createDataFrame([], SCHEMA).write.parquet(f"{d}/documents.parquet")
    return d


@pytest.fixture(scope="module")
def texts(spark, sf):
    return {r.doc_id: r for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}


@pytest.mark.parametrize("name", sorted(OPS))
def test_odd_and_empty_tables(spark, odd, empty, name):
    rows = OPS[name](spark, odd).collect()
    assert len(rows) == len(ODD)
    if name != "op4_probminhash":
        assert Counter(r.doc_id for r in rows) == Counter(r[0] for r in ODD)
    assert OPS[name](spark, empty).collect() == []


# ---- 1 ----


@pytest.mark.parametrize("n", [0, 1, 63, 64, 65, 170, 176, 184, 32704, 32705, 100_000])
def test_transport_round_trip(n):
    payload = np.random.default_rng(n).integers(0, 256, n, dtype=np.uint8).tobytes()
    got = op1_transport.demux(op1_transport.mux(payload))
    assert got["payload"] == payload
    assert got["counter_faults"] == got["sync_faults"] == got["table_faults"] == 0
    assert got["programs"] == {1: 0x1000} and got["streams"] == {0x100: 6}
    assert [u[1] for u in got["units"]] == [i * 3600 for i in range(max(1, -(-n // 32704)))]
    assert all(u[3] for u in got["units"])


def test_transport_faults_are_counted():
    s = bytearray(op1_transport.mux(bytes(range(256)) * 20))
    del s[188 * 6 : 188 * 7]
    s[188 * 9] = 0
    got = op1_transport.demux(bytes(s))
    assert got["counter_faults"] >= 1 and got["sync_faults"] == 1
    assert op1_transport.demux(b"")["payload"] == b""
    assert op1_transport.demux(b"\x47" * 100)["packets"] == 0


def test_transport_tables_over_packets():
    """Sections longer than a packet, several in one packet, and sync found again after lost bytes."""
    o = op1_transport
    pmts = [o._section(2, n, bytes([0xE1, 0, 0xF0, 0]) + b"".join(bytes([6, 0xE0 | (0x200 + n) >> 8, (0x200 + n) & 255, 0xF0, 100]) + bytes(100) for _ in range(3))) for n in range(2)]
    pat = o._section(0, 1, b"".join(bytes([0, n + 1, 0xF0 + n, 0]) for n in range(2)))
    def carried(pid, data):
        out, body = [], b"\0" + data
        for k, at in enumerate(range(0, len(body), 184)):
            out.append((bytes([0x47, (0x40 if k == 0 else 0) | pid >> 8, pid & 255, 0x10 | k]) + body[at : at + 184]).ljust(188, b"\xff"))
        return b"".join(out)
    got = o.demux(carried(0, pat) + carried(0x1000, pmts[0]) + carried(0x1100, pmts[1]))
    assert got["programs"] == {1: 0x1000, 2: 0x1100} and got["streams"] == {0x200: 6, 0x201: 6} and got["table_faults"] == 0
    both = o.demux(carried(0, pat + pat) + carried(0x1000, pmts[0] + pmts[0])[: 188 * 5])
    assert both["streams"] == {0x200: 6} and both["table_faults"] == 0
    assert o.demux(carried(0, pat) + carried(0x1000, pmts[0])[:188])["table_faults"] == 1
    s = o.mux(bytes(range(200)) * 300)
    lost = o.demux(s[: 188 * 40 + 50] + s[188 * 40 + 90 :])
    assert lost["sync_faults"] == 1 and lost["packets"] >= len(s) // 188 - 2 and lost["counter_faults"] >= 1


def test_transport_keeps_other_columns(spark):
    df = spark.createDataFrame([(1, "abc", "x", 5, "y")], "doc_id long, text string, Media string, n_bytes int, _made string")
    row = op1_transport.read_back(op1_transport.store(df)).first()
    assert (row.n_bytes, row.payload_bytes, row._made, row.text) == (3, 64, "y", "abc") and bytes(row.media[:1]) == b"G"


def test_transport_query(spark, sf, texts):
    for r in OPS["op1_transport_stream"](spark, sf).collect():
        n, p = op1_transport.padded(texts[r.doc_id].text)
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (n, len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]))
        s = op1_transport.mux(p)
        assert (r.media_bytes, r.media_sha256) == (len(s), hashlib.sha256(s).hexdigest())


# ---- 2 ----


def test_language_accuracy(spark, sf, texts):
    rows = OPS["op2_language_zstd"](spark, sf).collect()
    for r in rows:
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0)
        assert 0 <= r.score <= 1
    held = [r for r in rows if r.held_out]
    assert np.mean([r.lang_pred == texts[r.doc_id].lang for r in held]) >= 0.97


def test_language_rejects(spark, odd):
    got = {r.doc_id: r for r in OPS["op2_language_zstd"](spark, odd).collect()}
    assert all(got[i].lang_pred == "und" and got[i].rejected for i in (3, 4, 6))


# ---- 3 ----


def reference():
    import public_tokenizers as P
    import tiktoken

    with open(P.path("byte_bpe_multi_50k.tiktoken"), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_bpe_equals_library(spark, sf, odd, texts):
    enc = reference()
    for d, own in ((sf, {k: r.text for k, r in texts.items()}), (odd, {r[0]: r[1] for r in ODD})):
        for r in OPS["op3_byte_bpe"](spark, d).collect():
            t = own[r.doc_id] or ""
            ids = enc.encode_ordinary(t)
            assert r.n_tokens == len(ids)
            assert r.ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
            assert r.decoded_sha256 == hashlib.sha256(t.encode()).hexdigest()


def test_bpe_folds_agree(spark, texts):
    """The sorted fold, the step fold and the library give the same ids; decoding gives the bytes back."""
    enc, codec = reference(), op3_byte_bpe.public_codec(spark)
    words = sorted({w for r in list(texts.values())[:40] for w in codec_split(r.text)})[:1500] + ["=" * 90, "日本語" * 9, "ñÑß" * 30]
    df = codec.bound(spark.createDataFrame([(w,) for w in words], "w string").repartition(4))
    rows = df.select("w", F.element_at(codec.fold(F.array("w")), 1).alias("ids")).collect()
    assert all(r.ids == enc._core_bpe.encode_single_piece(r.w.encode()) for r in rows)
    h = F.hex(F.encode("w", "UTF-8"))
    step = df.where(F.octet_length("w") > 1).select("w", common.let(F.col("_ranks"), lambda t: codec._step_fold(t, h)).alias("ids")).collect()
    own = op3_byte_bpe.Words.__new__(op3_byte_bpe.Words)
    own.rank = {p: i for i, p in enumerate(codec.raw)}
    for r in step:
        want = enc._core_bpe.encode_single_piece(r.w.encode())
        assert r.ids == want or len(want) == 1
        assert own.fold(r.w.encode()) == want
    back = codec.bound(spark.createDataFrame([([1, 2, 300],), ([],)], "ids array<int>")).select("ids", codec.decode(F.col("ids")).alias("b"), codec.id_bytes(F.col("ids")).alias("i"))
    for r in back.collect():
        assert bytes(r.b) == b"".join(codec.raw[i] for i in r.ids)
        assert bytes(r.i) == np.array(r.ids, "<u4").tobytes()


def codec_split(text):
    from evigraph.llm.splitting import splitter

    return splitter()(text)


def test_splitter_equals_pattern():
    import public_tokenizers as P
    import regex

    from evigraph.llm.splitting import splitter

    full = regex.compile(P.PATTERN).findall
    for t in ["it's we'll I'D", "a_b 1_2 __", " \n\n x  y ", "½ ² Ⅷ 一 十", "naïve ÑÑ ß_1", "\x1c\x1f \x85", "\U0001f600\U0001d7d8 9", "é ​　z", ""]:
        assert splitter()(t) == full(t), t


# ---- 4 ----


def test_hashes_are_independent_of_place():
    a = hashing.word_hashes("alpha beta gamma")
    assert list(hashing.word_hashes("x ALPHA, beta; gamma")[1:]) == list(a)
    long = "w1 " * 300_000 + "tail"
    assert len(hashing.word_hashes(long)) == 300_001
    assert len(hashing.shingles(a, 5)) == 1 and len(hashing.shingles(hashing.word_hashes(""), 5)) == 0


def test_registers_estimate_probability_jaccard():
    rng = np.random.default_rng(3)
    x = (np.arange(200, dtype=np.uint64), rng.integers(1, 5, 200))
    y = (np.arange(60, 260, dtype=np.uint64), rng.integers(1, 5, 200))
    sims = []
    for turn in range(30):
        s = op4_probminhash.signatures([(hashing.mix(x[0] + np.uint64(turn * 1000)), x[1]), (hashing.mix(y[0] + np.uint64(turn * 1000)), y[1])])
        sims.append((s[0] == s[1]).mean())
    assert np.mean(sims) == pytest.approx(op4_probminhash.similarity(x, y), abs=0.03)
    p, q = dict(zip(x[0].tolist(), x[1].tolist())), dict(zip(y[0].tolist(), y[1].tolist()))
    naive = sum(1 / sum(max(p.get(e, 0) / p[d], q.get(e, 0) / q[d]) for e in {*p, *q}) for d in p if d in q)
    assert op4_probminhash.similarity(x, y) == pytest.approx(naive)


def classes_by_force(own: dict) -> dict:
    sets = {i: op4_probminhash.weighted(t) for i, t in own.items() if t is not None}
    root = {i: i for i in own}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for k, i in enumerate(ids):
        for j in ids[:k]:
            if own[i] == own[j] or op4_probminhash.similarity(sets[i], sets[j]) >= 0.8:
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return {i: find(i) for i in own}


def test_classes_equal_brute_force(spark, sf, texts):
    got = {r.doc_id: r.class_id for r in OPS["op4_probminhash"](spark, sf).collect()}
    assert got == classes_by_force({k: r.text for k, r in texts.items()})


def test_star_of_copies(spark, tmp_path):
    """Copies of one text, each with its own edits: alike to the original more than to each other."""
    rng = np.random.default_rng(5)
    words = [f"word{i}" for i in rng.integers(0, 5000, 400)]
    rows = [(500, " ".join(words))]
    for i in range(120):
        w = list(words)
        for at in rng.choice(400, 7, replace=False):
            w[at] = f"edit{i}x{at}"
        rows.append((i, " ".join(w)))
    rows += [(1000 + i, " ".join(f"other{i}n{j}" for j in range(60))) for i in range(20)]
    spark.createDataFrame([(i, t, "en", "s", 1) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: r.class_id for r in OPS["op4_probminhash"](spark, str(tmp_path)).collect()}
    assert got == classes_by_force(dict(rows))
    assert len({got[i] for i in range(120)} | {got[500]}) == 1


@pytest.mark.parametrize("most", [20, 2048])
def test_pairs_of_a_crowd(spark, most):
    """Many texts at 0.75 to 0.79 to each other, with planted pairs over 0.8 that no hub joins."""
    words = [f"word{i}" for i in range(400)]
    rows = []
    for i in range(80):
        w, j = list(words), i % 40
        for k in range(5):  # any two of the 40 share at most one place of their edits
            w[5 * (13 * k + (j % 13 + j // 13 * k) % 13) + 5] = f"edit{j}x{k}"
        w[-1] = f"end{i}"
        rows.append((i, " ".join(w)))
    want = classes_by_force(dict(rows))
    sets = [op4_probminhash.weighted(t) for _, t in rows]
    others = [op4_probminhash.similarity(sets[i], sets[j]) for i in range(40) for j in range(i)]
    assert 0.75 <= min(others) and max(others) < 0.8
    assert want == {i: i % 40 for i in range(80)}
    got = {r._id: r.class_id for r in op4_probminhash.classes(spark.createDataFrame(rows, "doc_id long, text string"), most=most).collect()}
    assert got == want


@pytest.mark.parametrize("top", [1, 4, 30])
def test_blocks_compute_similarity(top):
    rng = np.random.default_rng(top)
    bags = [op4_probminhash.weighted(" ".join(f"w{x}" for x in rng.integers(0, 4, n)) + " " + " ".join(["a b c d e f"] * int(rng.integers(1, top + 1)))) for n in rng.integers(1, 60, 25)]
    bags.append((bags[0][0], bags[0][1] * 3))
    block, y = blocks.Block(bags), np.arange(26)
    for x in range(26):
        exact = np.array([blocks.similarity(bags[x], b) for b in bags])
        assert np.allclose(block.against(x, y), exact)
        for t in (0.1, 0.3, 0.5, 0.8):
            clear = abs(exact - t) > 1e-6
            assert (block.near(x, y, t) == (exact >= t))[clear].all()


@pytest.mark.parametrize("most", [3, 7, 100])
def test_blocks_leave_no_pair_apart(spark, most):
    rng = np.random.default_rng(most)
    texts = {n: " ".join(f"w{n % 6}x{i}" if rng.random() < 0.9 else f"e{n}x{i}" for i in range(40)) for n in range(60)}
    rows = [(b, 60, n) for b in range(2) for n in texts] + [(5, 2, 1), (5, 2, 2)]
    members, held = spark.createDataFrame(rows, "b long, n long, node long"), spark.createDataFrame(list(texts.items()), "node long, t string")
    bag = lambda t: (hashing.word_hashes(t), np.ones(40, int))
    dealt = blocks.parted(members, held, most)
    assert {r.b for r in dealt.collect()} == {0, 1} and {(r.a, r.b) for r in blocks.pairs(members).collect()} == {(2, 1)}
    links = blocks.within(dealt, held, bag, 0.8).distinct()
    roots = common.saved(components.components(links, "a", "b"), "roots")
    roots = components.joined_on(roots, common.saved(blocks.across(dealt, roots, held, bag, 0.8), "rest"))
    got = {r.node: r.root for r in roots.collect()}
    sets = {n: set(t.split()) for n, t in texts.items()}
    root = {n: n for n in texts}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for x in texts:
        for y in range(x):
            if len(sets[x] & sets[y]) / len(sets[x] | sets[y]) >= 0.8:
                a, b = find(x), find(y)
                root[max(a, b)] = min(a, b)
    assert {n: got.get(n, n) for n in texts} == {n: find(n) for n in texts}


def test_near_duplicates_of_odd_rows(spark):
    """Unequal texts with one id are nodes of their own; repeated rows, null ids and clashing names."""
    a, b, c = "one two three four five six", "ten nine eight seven six five", "red green blue black white grey"
    rows = [(5, a, "x", "y"), (5, b, "x", "y"), (7, b, "x", "y"), (8, c, "x", "y"), (8, c, "x", "y"), (None, a, "x", "y"), (9, None, "x", "y"), (9, None, "x", "y"), (10, "", "x", "y"), (11, "", "x", "y")]
    df = spark.createDataFrame(rows, "doc_id long, text string, _id string, _KEY string")
    got = op4_probminhash.deduplicated(df)
    assert got.columns == df.columns
    assert sorted((r.doc_id, r.text or "") for r in got.collect() if r.doc_id is not None) == [(5, b), (8, c), (9, ""), (9, ""), (10, "")]
    assert [r.text for r in got.collect() if r.doc_id is None] == [a]  # a missing id is a negative number, so the least
    told = op4_probminhash.classes(df).collect()
    assert len(told) == len(rows) and len({(r.class_id, r.class_key) for r in told}) == 5
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert op4_probminhash.deduplicated(empty).collect() == []


def test_components(spark):
    rng = np.random.default_rng(1)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 300, (220, 2))] + [(i, i + 1) for i in range(1000, 1040)]
    got = {r.node: r.root for r in components.components(spark.createDataFrame(edges, "a long, b long"), "a", "b").collect()}
    root = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for a, b in edges:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    assert got == {x: find(x) for a, b in edges if a != b for x in (a, b)}


# ---- 5 ----


@pytest.mark.parametrize("n,bits", [(2, 3), (3, 2), (4, 2)])
def test_hilbert_steps_to_neighbours(spark, n, bits):
    df = spark.range(1 << n * bits).select(*[F.shiftright("id", bits * i).bitwiseAND((1 << bits) - 1).alias(f"x{i}") for i in range(n)])
    rows = sorted((r[-1], tuple(r)[:n]) for r in df.withColumn("h", op5_hilbert.hilbert_index([F.col(f"x{i}") for i in range(n)], bits)).collect())
    assert [r[0] for r in rows] == list(range(1 << n * bits))
    assert all(sum(abs(p - q) for p, q in zip(a[1], b[1])) == 1 for a, b in zip(rows, rows[1:]))


def test_shards(spark, sf, texts):
    rows = OPS["op5_hilbert"](spark, sf).collect()
    n = Counter(r.shard for r in rows)
    assert set(n) == set(range(8)) and max(n.values()) - min(n.values()) <= 1
    for s in n:
        assert sorted(r.slot for r in rows if r.shard == s) == list(range(n[s]))
    ordered = [r.hilbert for r in sorted(rows, key=lambda r: (r.shard, r.slot))]
    assert ordered == sorted(ordered)
    assert all(r.size == len(texts[r.doc_id].text.encode()) + 1 and r.text_crc32 == zlib.crc32(texts[r.doc_id].text.encode()) for r in rows)


# ---- 6 ----


def test_licenses_equal_brute_force(spark, sf, texts):
    scan = op6_licenses.Scanner(op6_licenses.TEMPLATES)
    for r in OPS["op6_licenses"](spark, sf).collect():
        s = hashing.shingles(hashing.word_hashes(texts[r.doc_id].text), 5)
        want = set()
        for name, own, words in zip(scan.names, scan.sets, scan.words):
            for i in np.flatnonzero(np.isin(s, own)):
                if len(np.intersect1d(s[i : i + words], own)) / len(own) >= 0.8:
                    want.add(name)
        assert set(r.templates) == want


def test_licenses_in_long_texts():
    scan = op6_licenses.Scanner(op6_licenses.TEMPLATES)
    noise = " ".join(f"n{i}" for i in range(1234))
    for name, text in op6_licenses.TEMPLATES.items():
        found = scan.scan(f"{noise} {text} {noise}")
        assert name in {f[0] for f in found}, name
        assert all(f[1] == 1234 for f in found if f[0] == name)
    assert scan.scan(noise) == [] == scan.scan(None)


def test_dual_and_repeated_licenses():
    scan = op6_licenses.Scanner(op6_licenses.TEMPLATES)
    own = op6_licenses.TEMPLATES
    pairs = [("CC-BY-4.0", "CC-BY-NC-4.0"), ("CC-BY-NC-4.0", "CC-BY-4.0"), ("MIT", "MIT"), ("CC-BY-4.0", "CC-BY-4.0"), ("MIT-notice", "MIT-notice")]
    for first, second in pairs:
        n = len(hashing.word_hashes(own[first]))
        for at in range(64):
            found = scan.scan(" ".join(f"n{i}" for i in range(at)) + f" {own[first]} {own[second]} " + " ".join(f"m{i}" for i in range(90)))
            assert {(f[0], f[1]) for f in found} >= {(first, at), (second, at + n)}, (first, second, at)
            assert sum(f[0] == second for f in found) == 1 + (first == second)
            assert all(f[3] == 1 for f in found if f[0] in (first, second))


# ---- 7 ----


@pytest.mark.parametrize("values", [[], [0], [1] * 200, list(range(100)), [2**60, 5, 2**63, 7], [2**60] * 3, [2**53 - 1, 2**59, 1]])
def test_simple8b_round_trip(values):
    v = np.array(values, np.uint64)
    assert list(op7_simple8b.unpack(op7_simple8b.pack(v))) == list(v)


def test_simple8b_packs_tightly():
    ids = np.random.default_rng(0).integers(0, 50_000, 10_000)
    assert len(op7_simple8b.pack(ids)) < 10_000 / 3
    assert len(op7_simple8b.pack(np.ones(600))) == 10


def test_token_files(spark, sf, texts):
    import public_tokenizers as P
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    got, at = {r.doc_id: r for r in OPS["op7_simple8b"](spark, sf).collect()}, 0
    for k in sorted(texts):
        ids = [*tok.encode(texts[k].text or "", add_special_tokens=False).ids, 0]
        assert (got[k].start, got[k].n_tokens, got[k].ids_crc32) == (at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        at += len(ids)


def test_token_files_of_odd_rows(spark):
    """The literal of a special token, odd characters, null and equal ids, empty and long texts; ids and starts read back."""
    import public_tokenizers as P
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    texts = ["a<|endoftext|>b", "plain words, don't split", None, "", "\U0001f600 \u00bd \x1c", "tab\tand\u00a0space  ", "word " * 70_000, "same", "same"]
    rows = [(None if i % 4 == 0 else 7, t) for i, t in enumerate(texts)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = op7_simple8b.read_files(op7_simple8b.write_files(df, P.path("byte_bpe_50k.json"))).collect()
    want = Counter()
    for k, t in rows:
        ids = [*tok.encode(t or "", add_special_tokens=False).ids, 0]
        want[k, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())] += 1
    assert Counter((r.doc_id, r.n_tokens, r.ids_crc32) for r in got) == want
    at = 0
    for r in sorted(got, key=lambda r: r.start):
        assert r.start == at
        at += r.n_tokens
    assert [r.doc_id is None for r in sorted(got, key=lambda r: r.start)] == [True] * 3 + [False] * 6


# ---- 8 ----


def test_fingerprints(spark, sf, texts):
    got, ids = {r.doc_id: r for r in OPS["op8_weighted_sampling"](spark, sf).collect()}, sorted(texts)
    bag = lambda t: Counter(w for w in re.split(r"[\W_]+", t.lower()) if w)
    gaps = []
    for a, b in zip(ids, ids[1:] + ids[:1]):
        t, n = texts[a].text, texts[b].text
        e = t[: len(t) - len(t) // 4] + n[: len(t) // 4]
        assert got[a].edited_sha256 == hashlib.sha256(e.encode()).hexdigest() and got[a].n_chars == len(t)
        for other, near in ((e, got[a].near_edited), (n, got[a].near_next)):
            x, y = bag(t), bag(other)
            gaps.append(sum((x & y).values()) / max(1, sum((x | y).values())) - near)
    assert abs(np.mean(gaps)) < 0.02 and np.std(gaps) < 0.1
    same = defaultdict(set)
    for i in ids:
        same[texts[i].text].add(got[i].fingerprint)
    assert all(len(v) == 1 for v in same.values())


# ---- 9 ----


def test_lines_equal_brute_force(spark, sf, texts):
    first = {}
    for i in sorted(texts):
        for n, x in op9_fuzzy_lines.lines_of(texts[i].text):
            first.setdefault(x, (i, n))
    lines = list(first)
    sets = [set(hashing.char_shingles(x, op9_fuzzy_lines.K).tolist()) for x in lines]
    root = list(range(len(lines)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    seen = defaultdict(list)
    for i, s in enumerate(sets):
        hits = Counter(j for h in s for j in seen[h])
        for h in s:
            seen[h].append(i)
        for j, k in hits.items():
            if k / (len(s) + len(sets[j]) - k) >= 0.8:
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    keep = {}
    for i, x in enumerate(lines):
        keep[find(i)] = min(keep.get(find(i), first[x]), first[x])
    stay = set(keep.values())
    for r in OPS["op9_fuzzy_lines"](spark, sf).collect():
        t = texts[r.doc_id].text.split("\n")
        assert r.text == "\n".join(x for n, x in enumerate(t) if not x.strip() or (r.doc_id, n) in stay)


@pytest.mark.parametrize("most", [20, 2048])
def test_lines_of_a_crowd(spark, most):
    """Lines of one template just under 0.8 to each other, with pairs over it that are neither first nor neighbours."""
    rng = np.random.default_rng(9)
    base = "".join(chr(97 + i) for i in rng.integers(0, 26, 404))
    lines = []
    for i in range(60):  # lines i and i + 30 differ by one letter at the end, all others share at most one place of their edits
        x = list(base)
        for k in range(3):
            at = 10 * (13 * k + (i % 30 % 13 + i % 30 // 13 * k) % 13) + 8
            x[at : at + 2] = chr(256 + i % 30) * 2
        x[-1] = "0" if i < 30 else "1"
        lines.append("".join(x))
    long = "ab" * 20
    lines += [long, long * 4]  # the same shingles, one under 0.4 of the other's length
    sets = [set(hashing.char_shingles(x, op9_fuzzy_lines.K).tolist()) for x in lines]
    near = [(i, j) for i in range(62) for j in range(i) if len(sets[i] & sets[j]) / len(sets[i] | sets[j]) >= 0.8]
    assert near == [(i + 30, i) for i in range(30)] + [(61, 60)]
    rows = [(i, x) for i, x in enumerate(lines)]
    got = {r.doc_id: r.n_removed for r in op9_fuzzy_lines.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string"), most=most).collect()}
    assert got == {i: int(30 <= i < 60 or i == 61) for i in range(62)}


def test_far_lines_are_told_by_bounds(monkeypatch):
    """Only pairs that bit tables leave open are worked out; the links are those of all pairs."""
    rng = np.random.default_rng(3)
    lines = ["".join(map(chr, rng.integers(97, 123, 300))) for _ in range(40)]
    lines += [x[:150] + y[:150] for x, y in zip(lines, lines[1:])] + [x[:-5] + "12345" for x in lines[:8]] + ["ab" * 9, "ab" * 90]
    pairs = [(a, b) for b in range(len(lines)) for a in range(b + 1, len(lines))]
    sets = [np.unique(hashing.char_shingles(x, op9_fuzzy_lines.K)) for x in lines]
    exact = {(a, b): len(np.intersect1d(sets[a], sets[b])) / len(np.union1d(sets[a], sets[b])) for a, b in pairs}
    near, calls = [p for p in pairs if exact[p] >= 0.8], []
    jaccard = op9_fuzzy_lines.jaccard
    monkeypatch.setattr(op9_fuzzy_lines, "jaccard", lambda x, y: calls.append(1) or jaccard(x, y))
    a, b = zip(*pairs)
    batch = pa.RecordBatch.from_arrays([pa.array(a), pa.array(b), pa.array([lines[i] for i in a]), pa.array([lines[i] for i in b])], names=["a", "b", "s", "t"])
    got = [p for out in op9_fuzzy_lines._verify(iter([batch])) for p in zip(out.column(0).to_pylist(), out.column(1).to_pylist())]
    assert sorted(got) == sorted(near) and len(near) >= 9 and len(calls) <= 2 * len(near)
    size = np.array([len(x) - 7 for x in lines])
    sign = blocks.signs(len(lines), np.repeat(np.arange(len(lines)), [len(x) for x in sets]), np.concatenate(sets))
    most = blocks.at_most(sign[list(a)], sign[list(b)], size[list(a)], size[list(b)])
    assert (most >= [exact[p] - 1e-9 for p in pairs]).all()


@pytest.mark.parametrize("k", [1, 3, 7, 8, 13])
def test_runs_equal_prefix_sums(k):
    values = hashing.mix(np.arange(40, dtype=np.uint64))
    at = np.arange(41 - k)
    assert (hashing.mix(hashing.runs(values, k)) == hashing.spans(hashing.prefix(values), at, at + k)).all()


def test_members_of_large_parts(spark, sf):
    """Buckets of parts that are too large for a task are counted by Spark, with the same members."""
    docs = spark.read.parquet(f"{sf}/documents.parquet").where("text is not null").selectExpr("text t")
    told = [sorted(op9_fuzzy_lines._members(docs, held).select("b", "node", "n").collect()) for held in (0, 7, op9_fuzzy_lines.HELD)]
    assert told[0] == told[1] == told[2] and len(told[0]) > 10
    lines = {x for r in docs.collect() for _, x in op9_fuzzy_lines.lines_of(r.t) if len(x) > op9_fuzzy_lines.K}
    buckets = defaultdict(set)
    for x in lines:
        for b in op9_fuzzy_lines.bands([x])[0].tolist():
            buckets[b].add(op9_fuzzy_lines.line_hash(x))
    assert {tuple(r) for r in told[0]} == {(b, h, len(v)) for b, v in buckets.items() if len(v) > 1 for h in v}


def test_common_line_leaves_a_block_once():
    """Of a line that stands everywhere a block sends one place to compare; the others go, but for rows that repeat a document."""
    n = 500
    batch = pa.RecordBatch.from_arrays([pa.array([7, 7, *range(8, 6 + n)]), pa.array([1, 1, *range(8, 6 + n)]), pa.array(["a line that all have\nx"] * n)], names=["id", "th", "t"])
    got = [(kind, op9_fuzzy_lines._array(x, 4 if kind == op9_fuzzy_lines.PLACE else 3)) for _, kind, x in op9_fuzzy_lines._unpacked(op9_fuzzy_lines._places(iter([batch]), 16))]
    assert sum(x.shape[1] for kind, x in got if kind == op9_fuzzy_lines.PLACE) == 2
    gone = {tuple(c) for kind, x in got if kind == op9_fuzzy_lines.REPEAT for c in x.T.tolist()}
    assert gone == {(i, i, no) for i in range(8, 6 + n) for no in (0, 1)}


def test_lines_of_odd_rows(spark):
    """Null ids and unequal texts with one id are documents of their own; repeated rows are one document."""
    x, y = "a line that stands in many texts", "quite another line of some length"
    rows = [(None, f"{x}\n1st", "p", "q"), (None, f"{x}\n2nd", "p", "q"), (None, f"{x}\n3rd", "p", "q"), (4, f"{y}\n\nz", "p", "q"), (4, f"{y}\n\nz", "p", "q"), (4, y, "p", "q"), (6, None, "p", "q"), (7, "", "p", "q")]
    df = spark.createDataFrame(rows, "doc_id long, text string, _id string, _STAY string")
    got = op9_fuzzy_lines.dedup_lines(df).collect()
    assert sum(x in r.text for r in got if r.doc_id is None) == 1 and len(got) == len(rows)
    assert {sum(y in r.text for r in got if r.doc_id == 4)} <= {1, 2}  # the text that hashes least keeps it: both equal rows, or the third
    assert [r.text for r in got if r.doc_id == 6] == [None] and [r.text for r in got if r.doc_id == 7] == [""]
    assert all((r._id, r._STAY) == ("p", "q") for r in got)


# ---- 10 ----


def test_mixture(spark, sf, texts):
    rows = OPS["op10_mixture"](spark, sf).collect()
    src = defaultdict(lambda: [0, 0, 0.0])
    for r in rows:
        assert r.size == len(re.findall(r"[^\x20\x09-\x0D]+", texts[r.doc_id].text)) and 0 <= r.taken <= 2 * r.size
        s = src[texts[r.doc_id].source]
        s[0] += r.size
        s[1] += r.taken
        s[2] = r.target
    total, names = sum(s[0] for s in src.values()), sorted(src)
    weight = {n: (5, 2, 1)[i % 3] for i, n in enumerate(names)}
    full: set = set()
    while True:
        left = 1.5 * total - sum(2 * src[n][0] for n in full)
        share = {n: left * weight[n] / sum(weight[m] for m in names if m not in full) for n in names if n not in full}
        over = {n for n, v in share.items() if v > 2 * src[n][0]}
        if not over:
            break
        full |= over
    for n in names:
        assert src[n][2] == pytest.approx(2 * src[n][0] if n in full else share[n])
        assert abs(src[n][1] - src[n][2]) <= 1
    assert sorted(rows) == sorted(OPS["op10_mixture"](spark, sf).collect())


def test_draws_are_permutations(spark):
    s = spark.createDataFrame([("'a", 10_000, 17_000.0), ("'b", 300, 600.0), ("'c", 5, 2.0)], "s string, source_size long, target double")
    rows = op10_mixture.draws(s, 64).collect()
    for name, size, want in (("'a", 10_000, 17_000), ("'b", 300, 600), ("'c", 5, 2)):
        own = [r for r in rows if r.s == name]
        assert sum(r.words for r in own) == want
        for p in {r["pass"] for r in own}:
            blocks = [r.block for r in own if r["pass"] == p]
            assert len(blocks) == len(set(blocks)) and max(blocks) <= size // 64
    counts = op10_mixture.shard_counts(op10_mixture.draws(s, 64)).groupBy("s").agg(F.sum("words").alias("w")).collect()
    assert {r.s: r.w for r in counts} == {"'a": 17_000, "'b": 600, "'c": 2}
    own = [r.blocks for r in op10_mixture.shard_counts(op10_mixture.draws(s, 64)).collect() if r.s == "'a"]
    mean = 17_000 / 64 / op10_mixture.SHARDS
    assert len(own) == op10_mixture.SHARDS and sum((x - mean) ** 2 / mean for x in own) < 30  # chi-square of 7 degrees of freedom


def test_mixture_by_force(spark, sf, texts):
    """Words taken of each document and shard, from the draws and the streams in order of id."""
    rows, sources = op10_mixture.plan(op10_mixture.prepared(spark.read.parquet(f"{sf}/documents.parquet")))
    drawn = defaultdict(list)
    for r in op10_mixture.draws(sources).collect():
        drawn[r.s].append(r)
    words, at = {i: re.findall(r"[^\x20\x09-\x0D]+", t.text or "") for i, t in texts.items()}, defaultdict(int)
    start = {}
    for i in sorted(texts):
        s = "n" if texts[i].source is None else "'" + texts[i].source
        start[i] = (s, at[s])
        at[s] += len(words[i])
    want = {i: Counter() for i in texts}
    for i, (s, a) in start.items():
        for d in drawn[s]:
            n = min(a + len(words[i]), d.block * 256 + d.words) - max(a, d.block * 256)
            if n > 0:
                want[i][d.shard] += n
    for r in OPS["op10_mixture"](spark, sf).collect():
        assert {x.shard: x.words for x in r.shards} == dict(want[r.doc_id]) and r.taken == sum(want[r.doc_id].values())


def test_mixture_of_repeated_rows(spark):
    """Rows that repeat id, text and source each have their own words in the mix; names that the operator uses itself are kept."""
    rows = [(1, " ".join(f"a{i}" for i in range(700)), "s", "k")] * 3 + [(None, " ".join(f"b{i}" for i in range(300)), None, "k")] * 2 + [(2, "", "s", "k"), (3, None, "s", "k")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, _key string").withColumn("_TIE", F.lit("t"))
    got = op10_mixture.mixed(df)
    assert got.columns == df.columns
    rows = got.collect()
    n = Counter()
    for r in rows:
        n[r.source] += len(r.text.split())
        assert (r._key, r._TIE) == ("k", "t")
    want = {r.s: r.target for r in op10_mixture.plan(op10_mixture.prepared(df))[1].collect()}
    assert abs(n["s"] - want["'s"]) <= 1 and abs(n[None] - want["n"]) <= 1


# ---- pipeline ----


def test_pipeline(spark, sf, odd, texts):
    import corpus_pipeline as cp

    docs, before = spark.read.parquet(f"{sf}/documents.parquet"), None
    assert [n for n, _ in cp.STAGES] == ["language", "lines", "near_duplicates", "mixture", "tokens"]
    for name, stage in cp.STAGES:
        docs = common.saved(stage(spark, docs, sf), name)
        rows = docs.collect()
        if name != "tokens":
            assert docs.columns == cp.COLUMNS
        if name == "language":
            assert len(rows) >= 0.98 * len(texts)
        if name == "near_duplicates":
            own = classes_by_force({r.doc_id: r.text for r in before})
            assert {r.doc_id for r in rows} == set(own.values())
        if name == "mixture":
            words = lambda rs: sum(len(re.findall(r"[^\x20\x09-\x0D]+", r.text)) for r in rs)
            assert words(rows) == pytest.approx(1.5 * words(before), abs=30)
            assert max(Counter(r.doc_id for r in rows).values()) <= 2
        if name == "tokens":
            enc = reference()
            want = Counter(hashlib.sha256(np.array(enc.encode_ordinary(r.text), "<u4").tobytes()).hexdigest() for r in before)
            assert Counter(r.ids_sha256 for r in rows) == want
            assert all(r.decoded_sha256 for r in rows)
        before = rows
    assert cp.run(spark, odd).count() > 0
    assert json.dumps(cp.ORACLE_SQL) == "null"
