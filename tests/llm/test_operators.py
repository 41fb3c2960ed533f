"""Each operator against the library it reproduces or a brute-force version, on small and awkward inputs."""

import base64
import functools
import hashlib
import math
import random
import struct
import zlib
from collections import Counter

import numpy as np
import pytest
import public_tokenizers as P
import tiktoken
import xxhash
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from hubloom.llm import registry
from hubloom.llm.bpe import Encoder, bpe_documents, decode_column, encode_column, load_ranks
from hubloom.llm.common import connected_components, texts
from hubloom.llm.decontamination import contaminated
from hubloom.llm.katz import LARGEST, LEFT, _narrow, discounts, held_out_id, katz_scores
from hubloom.llm.line_templates import drop_recurring_lines
from hubloom.llm.quality import _kth_largest, gumbel, label_sample, ngram_buckets, resample, score_documents
from hubloom.llm.runindex import RunIndex, remove_repeats
from hubloom.llm.simhash import component_stars, exact_bands, fingerprint, simhash_components, within_radius
from hubloom.llm.syncmers import syncmer_fingerprints
from hubloom.llm.token_counts import PreTokens, frequent_pretokens, token_counts
from hubloom.llm.warc import archive_and_read

RANKS = P.path("byte_bpe_multi_50k.tiktoken")
ODD = "aàbTHE 's  \n\t\r\x0b\x0c\x1c\x85\xa0éñßΣσİıǅ中文字한국123٣½²!?.,<|>😀é\x00"


def docs_of(spark, rows):
    """Documents with null columns and columns whose names the operators use themselves."""
    full = [(i, t, None, "s", 1, 7, 8) for i, t in rows]
    return spark.createDataFrame(full, "doc_id long, text string, lang string, source string, n_chars long, row long, fp long")


def awkward(rnd, n=40):
    """Awkward texts: empty, null, repeated rows, a null id, long runs."""
    words = ["alpha", "beta", "gamma", "x1", "delta.", "Eps"]
    rows = [(i, " ".join(rnd.choice(words) for _ in range(rnd.randint(0, 30)))) for i in range(n)]
    return [*rows, (n, ""), (n + 1, None), (n + 2, "a" * 5000), (n + 3, " " * 3000), (3, rows[3][1]), (None, "alpha beta gamma delta."), (n + 4, ODD * 3)]


@pytest.fixture(scope="module")
def library():
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(RANKS, "rb"))}
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_bpe_equals_the_library(library):
    rnd = random.Random(1)
    some = ["".join(rnd.choice(ODD) for _ in range(rnd.randint(0, 90))) for _ in range(800)]
    some += ["", " " * 4000 + "a", "b" * 3000, "ab" * 2000, "<|endoftext|>"]
    got = Encoder(load_ranks(RANKS), P.PATTERN).encode(some)
    for text, packed in zip(some, got, strict=True):
        ids = library.encode_ordinary(text)
        assert packed == struct.pack(f"<{len(ids)}I", *ids)


def test_bpe_columns_round_trip(spark):
    rows = awkward(random.Random(2))
    docs = texts(docs_of(spark, rows))
    got = bpe_documents(docs, RANKS, P.PATTERN).collect()
    assert sorted(bytes(r["decoded"]) for r in got) == sorted((t or "").encode() for _, t in rows)
    both = docs.select("text", decode_column(encode_column(F.col("text"), RANKS, P.PATTERN), RANKS).alias("back"))
    assert both.where(F.col("text").cast("binary") != F.col("back")).isEmpty()
    assert bpe_documents(docs.limit(0), RANKS, P.PATTERN).collect() == []


def test_token_counts_equal_the_library(spark):
    path = P.path("word_bpe_49k.json")
    tok = Tokenizer.from_file(path)
    rows = [*awkward(random.Random(3)), (100, "<|startoftext|>Hi<|endoftext|> there ΑΣ"), (101, "don't WE'LL 12 3\n")]
    got = Counter((r["doc_id"], r["n_bytes"], r["n_tokens"], r["over_limit"]) for r in token_counts(texts(docs_of(spark, rows)), path, 50).collect())
    want = Counter((i, len((t or "").encode()), n := len(tok.encode(t or "", add_special_tokens=False).ids), n > 50) for i, t in rows)
    assert got == want
    pre = PreTokens(path)
    rnd = random.Random(4)
    for _ in range(400):
        s = "".join(rnd.choice(ODD) for _ in range(40))
        assert sum(pre.length(w) for w in pre.cut(s)) == len(tok.encode(s, add_special_tokens=False).ids) or "<|" in s
    assert "alpha" in frequent_pretokens(texts(docs_of(spark, rows)), path, size=8)


def test_warc(spark):
    pages = [(0, "http://a.example.com/x?q=1#f", "<p>one\r\n\r\nWARC/1.1\r\n</p>"), (1, "https://b.example.org/", "same"), (2, "https://www.b.example.org:8080/u", "same"), (3, None, None), (4, "", ""), (5, "http://a.example.com/x?q=1", "é" * 100), (None, "http://c.net/ \n", "same"), (7, "not a url", "z" * 200_000)]
    df = spark.createDataFrame([(*p, 1) for p in pages], "page_id long, url string, html string, digest int")
    got = {r["page_id"]: r for r in archive_and_read(df).collect()}
    assert len(got) == len(pages)
    first: dict[bytes, int] = {}
    for i, _, html in sorted((p for p in pages if p[0] is not None)):
        raw = (html or "").encode()
        digest = base64.b32encode(hashlib.sha1(raw).digest()).decode()
        f = first.setdefault(raw, i)
        r = got[i]
        assert (r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) == (len(raw), digest, "response" if f == i else "revisit", None if f == i else f)
        assert r["payload"] == ((html or "") if f == i else None)
    assert got[None]["refers_to"] == 1
    assert archive_and_read(df.limit(0)).collect() == []


def test_bit_sliced_comparison():
    rng = np.random.default_rng(5)
    for radius, width in ((4, 64), (46, 256), (0, 64)):
        prints = rng.integers(0, 256, (200, width // 8), dtype=np.uint8)
        for i in range(1, 200, 3):  # near copies
            bits = np.unpackbits(prints[i - 1])
            bits[rng.choice(width, min(width, radius + rng.integers(-2, 3) if radius > 2 else radius), replace=False)] ^= 1
            prints[i] = np.packbits(bits)
        distance = np.unpackbits(prints[:, None] ^ prints[None], axis=2).sum(axis=2)
        bits = np.unpackbits(prints, axis=1)
        planes = np.zeros((width, 4), dtype=np.uint64)
        for lane in range(200):
            planes[:, lane // 64] |= bits[lane].astype(np.uint64) << np.uint64(lane % 64)
        q, w = np.repeat(np.arange(200), 4), np.tile(np.arange(4), 200)
        got = np.unpackbits(within_radius(bits, q, w, planes, radius).astype("<u8").view(np.uint8).reshape(200, -1), axis=1, bitorder="little")[:, :200]
        assert (got == (distance <= radius)).all()
        for runs in (np.arange(200) // 20, np.zeros(200, dtype=int)):  # runs of one word, and one of several
            a, b = component_stars(prints, runs, radius)
            root = list(range(200))
            for x, y in zip(a, b, strict=True):
                assert runs[x] == runs[y]
                root[x] = y
            want = list(range(200))
            for _ in range(12):
                for x in range(200):
                    want[x] = min(want[y] for y in range(200) if runs[x] == runs[y] and distance[x, y] <= radius)
            groups = lambda r: sorted(Counter(r).values())
            assert groups(root) == groups(want)


def test_exact_bands_miss_nothing():
    rnd = random.Random(6)
    bands = exact_bands(64, 4)
    for _ in range(300):
        changed = set(rnd.sample(range(64), 4))
        assert any(not changed & set(b) for b in bands)


def test_simhash_components(spark):
    rnd = random.Random(7)
    base = [" ".join(rnd.choice("abcdefghij") + str(rnd.randrange(30)) for _ in range(120)) for _ in range(6)]
    rows = [(i, t) for i, t in enumerate(base)] + [(10 + i, t.replace("a1", "zz")) for i, t in enumerate(base)] + [(20, base[0].upper()), (21, ""), (22, " \t"), (23, None), (24, "one two"), (None, base[1]), (1, base[1])]
    got = {}
    for r in simhash_components(texts(docs_of(spark, rows))).collect():
        got.setdefault(r["doc_id"], set()).add((bytes(r["fp"]), r["component_id"]))
    fps = {}
    for i, t in rows:
        words = (t or "").encode().lower().split()
        k = min(4, len(words))
        hs = [xxhash.xxh64_intdigest(b" ".join(words[j : j + k]), 42) for j in range(len(words) - k + 1)] if words else []
        fps[i] = sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))
        assert fingerprint(t or "", 4) == fps[i].to_bytes(8, "big")
    ids = sorted(i for i in fps if i is not None)
    root = {i: i for i in ids}
    for _ in ids:
        for a in ids:
            root[a] = min(root[b] for b in ids if (fps[a] ^ fps[b]).bit_count() <= 4)
    for i in ids:
        assert got[i] == {(fps[i].to_bytes(8, "big"), root[i])}
    assert simhash_components(texts(docs_of(spark, rows[:0]))).collect() == []


def test_components_of_chains_and_stars(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 100 + i) for i in range(1, 30)] + [(7, 7)]
    got = {r["node"]: r["root"] for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {i: 0 for i in range(41)} | {100 + i: 100 for i in range(30)}


def test_syncmers(spark):
    rnd = random.Random(8)
    rows = [*awkward(rnd, 30), (90, "".join(rnd.choice("abcdefgh ") for _ in range(4000))), (91, "".join(rnd.choice("ijklmnop ") for _ in range(4000)))]
    got = syncmer_fingerprints(texts(docs_of(spark, rows))).collect()
    order = sorted(((-(2**63) if i is None else i, t or "") for i, t in rows))
    want = Counter()
    for (i, t), (_, u) in zip(order, order[1:] + order[:1], strict=True):
        n = len(t) // 4
        want[(None if i == -(2**63) else i, len(t), hashlib.sha256((t[: len(t) - n] + u[:n]).encode()).hexdigest())] += 1
    assert Counter((r["doc_id"], r["n_chars"], r["edited_sha256"]) for r in got) == want
    by = {r["doc_id"]: r for r in got}
    assert by[90]["near_edited"] > 0.3 and by[90]["near_next"] < 0.05
    assert len({r["fingerprint"] for r in got if r["doc_id"] == 3}) == 1
    assert all(0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1 for r in got)


def test_run_index_ranks_and_samples():
    rnd = random.Random(9)
    units = ["".join(rnd.choice("ab") for _ in range(rnd.randint(6, 30))).encode() for _ in range(50)]
    index = RunIndex(units, 6)
    unit, start, least = index.stream()
    assert len(unit) == sum(len(u) - 5 for u in units)
    for u, s, low in zip(unit.tolist(), start.tolist(), least.tolist(), strict=True):
        assert low == next(i for i, x in enumerate(units) if units[u][s : s + 6] in x)
    text = b"\xff".join(units) + b"\xff"
    suffix = lambda p: (text[p : text.index(b"\xff", p)], text[:p].count(b"\xff"))
    order = sorted(range(len(text)), key=suffix)
    assert [index.locate(r) for r in range(0, len(text), 7)] == order[::7]


@pytest.mark.parametrize("hot", [False, True])
def test_repeats_against_brute_force(spark, monkeypatch, hot):
    if hot:
        monkeypatch.setattr("hubloom.llm.runindex.HOT_PIECES", 2)
    rnd = random.Random(10)
    text = lambda n: "".join(rnd.choice("abcdé ") for _ in range(n))
    shared = [text(60), text(200), "ab" * 60]
    rows = [(i, text(rnd.randint(0, 300)) + rnd.choice(shared) + text(rnd.randint(0, 200))) for i in range(40)] + [(50, ""), (51, None), (52, shared[1]), (52, shared[1]), (53, shared[1][:49]), (None, shared[0])]
    got = Counter((r["doc_id"], r["n_bytes"], r["n_removed"], r["n_spans"], bytes(r["kept"])) for r in remove_repeats(texts(docs_of(spark, rows))).collect())
    want = Counter()
    where: dict[bytes, int] = {}
    for i, t in rows:
        raw, key = (t or "").encode(), -1 if i is None else i
        for j in range(len(raw) - 49):
            where[raw[j : j + 50]] = min(key, where.get(raw[j : j + 50], 10**9))
    for i, t in rows:
        raw, key = (t or "").encode(), -1 if i is None else i
        gone = bytearray(len(raw))
        for j in range(len(raw) - 49):
            if where[raw[j : j + 50]] < key:
                gone[j : j + 50] = b"\1" * 50
        spans = sum(1 for j, g in enumerate(gone) if g and (j == 0 or not gone[j - 1]))
        want[(i, len(raw), sum(gone), spans, bytes(c for c, g in zip(raw, gone, strict=True) if not g))] += 1
    assert got == want


def test_katz_against_brute_force(spark):
    rows = awkward(random.Random(11), 60)
    got = katz_scores(texts(docs_of(spark, rows)), 2).collect()
    tokens = [(i, (t or "").encode().lower().split()) for i, t in rows]
    uni, bi, hist = Counter(), Counter(), Counter()
    for i, words in tokens:
        if not held_out_id(i):
            uni.update([*words, None])
            bi.update(zip(["<s>", *words], [*words, None], strict=True))
            hist.update(["<s>", *words])
    n, v = sum(uni.values()), len(uni)
    of_counts = lambda c: np.array([0, *[sum(x == r for x in c.values()) for r in range(1, LARGEST + 2)]], dtype=float)
    d1, d2 = discounts(of_counts(uni)), discounts(of_counts(bi))
    cut = lambda c, d: c * d[c] if c <= LARGEST else c - LEFT
    left = 1 - sum(cut(c, d1) for c in uni.values()) / n
    p1 = lambda w: cut(uni[w], d1) / n if uni[w] else left
    alpha = {h: (1 - sum(cut(c, d2) for (a, _), c in bi.items() if a == h) / hist[h]) / (1 - sum(p1(b) for (a, b) in bi if a == h)) for h in hist}
    p2 = lambda h, w: cut(bi[(h, w)], d2) / hist[h] if bi[(h, w)] else alpha.get(h, 1) * p1(w)
    for h in list(hist)[:5]:
        assert math.isclose(sum(p2(h, w) for w in uni) + p2(h, "never seen"), 1, rel_tol=1e-9)
    want = {}
    for i, words in tokens:
        seq = [*words, None]
        base = sum(math.log10((uni[w] + 0.5) / (n + 0.5 * (v + 1))) for w in seq)
        score = sum(math.log10(p2(h, w)) for h, w in zip(["<s>", *words], seq, strict=True))
        want.setdefault(i, []).append((held_out_id(i), len(seq), sum(uni[w] > 0 for w in seq), n, base, score))
    assert len(got) == len(rows)
    for r in got:
        assert any(tuple(r)[1:5] == w[:4] and math.isclose(r["base_score"], w[4], abs_tol=1e-8) and math.isclose(r["score"], w[5], abs_tol=1e-8) for w in want[r["doc_id"]])
    assert katz_scores(texts(docs_of(spark, []))).collect() == []
    assert _narrow(np.array([3, 2**33])).tolist() == [3, 2**33] and _narrow(np.array([3, 255])).dtype == np.uint8
    assert held_out_id(12) == (zlib.crc32(b"12") % 5 == 1)


def test_katz_of_higher_orders_against_recursion(spark):
    rnd = random.Random(5)
    rows = [(i, None if i == 7 else " ".join(rnd.choice("a b c d e f".split()) if rnd.random() < 0.9 else f"x{i}" for _ in range(rnd.randrange(25)))) for i in range(60)]
    rows += rows[:5]
    top = 3
    tokens = [(i, (t or "").encode().lower().split()) for i, t in rows]
    grams, hist = [Counter() for _ in range(top + 1)], Counter()
    for i, words in tokens:
        if not held_out_id(i):
            seq = ["<s>"] * (top - 1) + [*words, None]
            for at in range(top - 1, len(seq)):
                for j in range(1, top + 1):
                    grams[j][tuple(seq[at - j + 1 : at + 1])] += 1
                    hist[tuple(seq[at - j + 1 : at])] += 1
    d = [None] + [discounts(np.array([0, *[sum(x == r for x in g.values()) for r in range(1, LARGEST + 2)]], dtype=float)) for g in grams[1:]]
    cut = lambda c, j: c * d[j][c] if c <= LARGEST else c - LEFT
    n = sum(grams[1].values())
    left = 1 - sum(cut(c, 1) for c in grams[1].values()) / n

    @functools.cache
    def weight(h):
        after = [g[-1] for g in grams[len(h) + 1] if g[:-1] == h]
        return (1 - sum(cut(grams[len(h) + 1][(*h, w)], len(h) + 1) for w in after) / hist[h]) / (1 - sum(prob(h[1:], w) for w in after))

    def prob(h, w):
        j = len(h) + 1
        if c := grams[j][(*h, w)]:
            return cut(c, j) / (hist[h] if h else n)
        return left if not h else (weight(h) if hist[h] else 1) * prob(h[1:], w)

    known = [w for (w,) in grams[1]]
    for h in [h for h in hist if len(h) == 2][:20]:
        assert math.isclose(sum(prob(h, w) for w in known) + prob(h, "never seen"), 1, rel_tol=1e-9)
    for order in (1, 2, 3):
        got = katz_scores(texts(docs_of(spark, rows)), order).collect()
        assert len(got) == len(rows)
        want = {}
        for i, words in tokens:
            seq = ["<s>"] * (order - 1) + [*words, None]
            want[i] = sum(math.log10(prob(tuple(seq[at - order + 1 : at]), seq[at])) for at in range(order - 1, len(seq)))
        assert all(math.isclose(r["score"], want[r["doc_id"]], abs_tol=1e-8) for r in got)


def test_line_templates(spark):
    rows = [(i, f"Own line {chr(97 + i) * 3} {chr(98 + i) * 4} {chr(99 + i) * 2}\nPrinted on 2024-01-{i:02d} by user{i} at desk {i}\nAll rights are reserved by {'Ann' if i % 3 else 'Bob'}.\nshort") for i in range(20)]
    rows += [(30, None), (31, ""), (32, "\n\n"), (None, "All rights are reserved by Ann."), (5, rows[5][1])]
    got = drop_recurring_lines(texts(docs_of(spark, rows)), min_documents=5).collect()
    assert len(got) == len(rows)
    by = {r["doc_id"]: r for r in got}
    assert all("Printed" not in by[i]["text"] for i in range(1, 20)) and "Printed" in by[0]["text"]
    # Two of the three tokens after the leading ones agree: too few, so Ann's line (first under the null id) and Bob's recur each by itself.
    assert all("rights" not in by[i]["text"] for i in range(1, 20)) and "rights" in by[None]["text"] and "Bob" in by[0]["text"]
    assert all("Own line" in by[i]["text"] and "short" in by[i]["text"] for i in range(20))
    assert (by[30]["text"], by[31]["text"], by[32]["text"], by[32]["n_lines"]) == ("", "", "\n\n", 3)
    assert drop_recurring_lines(texts(docs_of(spark, []))).collect() == []
    plan = drop_recurring_lines(texts(docs_of(spark, rows)))._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_line_templates_of_one_leaf(spark):
    city = ["Rome", "Oslo", "Lima", "Cairo", "Quito", "Paris", "Delhi", "Minsk", "Sofia", "Tunis", "Hanoi", "Accra"]
    kinds = ["This page was seen from {} by a reader today", "This page was sold in {} for some money once"]
    rows = [(i, f"start {chr(97 + i)}\n{kinds[i % 2].format(city[i // 2])}\nend {chr(97 + i)}") for i in range(24)]
    got = {r["doc_id"]: r["text"] for r in drop_recurring_lines(texts(docs_of(spark, rows))).collect()}
    assert sorted(i for i in got if "page" in got[i]) == [0, 1]  # a template each, whose city varies
    # A long line in three texts goes; in copies of a text, or in near copies that start alike, it stays.
    long = "one line of well over eight tokens that some texts share"
    rows = [(i, f"start {chr(97 + i)}\n{long}\nend {chr(97 + i)}") for i in range(3)] + [(i, f"one start\n{long} too\nend {chr(97 + i)}") for i in range(4, 8)] + [(i, f"a copy\n{long} as well\nof it") for i in range(10, 30)]
    got = {r["doc_id"]: r["n_dropped"] for r in drop_recurring_lines(texts(docs_of(spark, rows))).collect()}
    assert sorted(i for i in got if got[i]) == [1, 2]


def test_decontamination(spark):
    items = spark.createDataFrame([(0, "A train leaves town at 3 km per hour and Mary walks 12 km to meet it before 9 in the evening"), (1, "short question with only five"), (2, None), (None, "x y z"), (3, "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu")], "item_id long, text string")
    same = "Filler words come first. A train leaves town at 3 km per hour and Mary walks 12 km to meet it before 9 in the evening. More."
    moved = same.replace("3 km", "47 km").replace("Mary", "John").replace("12", "800").replace("9", "11")
    rows = [(1, same), (2, moved), (3, "nothing of the kind is here at all, really nothing"), (4, None), (5, ""), (6, "so: short question with only five words"), (7, "alpha beta gamma delta one two three"), (8, "ALPHA beta gamma delta epsilon zeta eta theta iota kappa lambda mu"), (None, same), (1, same)]
    got = {(r["doc_id"], r["item_id"]) for r in contaminated(texts(docs_of(spark, rows)), items).collect()}
    assert got == {(1, 0), (2, 0), (6, 1), (8, 3), (None, 0)}
    # Values that don't map one to one: a template that agrees by chance.
    twice = spark.createDataFrame([(0, "add 5 to 5 then 5 more and 5 again until 5 remain of 5 things in 5 boxes for 5 people")], "item_id long, text string")
    odd = [(1, "add 5 to 5 then 5 more and 5 again until 5 remain of 5 things in 5 boxes for 5 people".replace("5", "{}").format(1, 2, 3, 4, 6, 7, 8, 9)), (2, "add 8 to 8 then 8 more and 8 again until 8 remain of 8 things in 8 boxes for 8 people")]
    assert {r["doc_id"] for r in contaminated(texts(docs_of(spark, odd)), twice).collect()} == {2}
    assert contaminated(texts(docs_of(spark, rows)), items.limit(0)).collect() == []
    assert contaminated(texts(docs_of(spark, [])), items).collect() == []


def test_quality(spark):
    rnd = random.Random(12)
    word = lambda: "".join(rnd.choice("aeioulnrst") for _ in range(rnd.randint(2, 4)))
    good = lambda: " ".join(word() for _ in range(80))
    bad = lambda: " ".join(word().upper() + "!!" for _ in range(80))
    toxic = lambda: " ".join(word() if rnd.random() > 0.1 else "vileword" for _ in range(80))
    rows = [(i, (bad if i % 10 == 0 else toxic if i % 10 == 1 else good)()) for i in range(600)] + [(900, None), (901, ""), (None, good())]
    labels = spark.createDataFrame([(i, int(i % 10 != 0), int(i % 10 == 1)) for i in range(0, 600) if i % 3] + [(None, 1, 0), (5, None, 0)], "doc_id long, quality int, toxic int")
    kept = {r["doc_id"] for r in resample(texts(docs_of(spark, rows)), labels).collect()}
    wrong = sum((i in kept) != (i % 10 > 1) for i in range(600))
    assert wrong <= 12
    assert len(resample(texts(docs_of(spark, rows)), labels, k=50).collect()) == 50
    assert len(resample(texts(docs_of(spark, rows)), labels.limit(0)).collect()) == len(rows)
    assert resample(texts(docs_of(spark, [])), labels).collect() == []


def test_quality_by_the_ratio_against_brute_force(spark):
    rnd = random.Random(31)
    rows = [(i, " ".join(rnd.choice(("clean words of many kinds stand here" if i % 4 else "vile junk words").split()) if rnd.random() < 0.2 else rnd.choice("some other words of a text".split()) for _ in range(rnd.randint(3, 60)))) for i in range(200)] + [(300, None), (7, "another text of one id"), (None, "vile")]
    labels = spark.createDataFrame([(i, int(i % 4 > 0), 0) for i in range(0, 200, 2)], "doc_id long, quality int, toxic int")
    sample = label_sample(labels)
    target_ids = set(sample.loc[sample["good"] & ~sample["fit"], "doc_id"])
    raw, target = Counter(), Counter()
    for i, t in rows:
        grams = ngram_buckets(t or "")[0].tolist()
        raw.update(grams)
        if i in target_ids:
            target.update(grams)
    share = sum(target.values()) / sum(raw.values())
    lr = {g: np.float32(math.log((target[g] + 2) / (raw[g] * share + 2))) for g in raw}
    want = {(i, t or ""): float(sum(lr[g] for g in ngram_buckets(t or "")[0].tolist())) for i, t in rows}
    docs = texts(docs_of(spark, rows))
    got = score_documents(docs, labels, weigh="ratio").join(docs.withColumn("row", F.xxhash64(F.coalesce("doc_id", F.lit(-(2**63))), "text")).select("row", "text"), "row").collect()
    assert len(got) == len(rows) and all(math.isclose(r["log_weight"], want[(r["doc_id"], r["text"])], abs_tol=1e-4) for r in got)
    best = sorted((r["key"] for r in got), reverse=True)
    assert sorted((r["key"] for r in resample(docs, labels, k=30, weigh="ratio").collect()), reverse=True) == best[:30]
    # Gumbel noise: its mean is Euler's constant.
    assert abs(spark.range(20000).select(F.avg(gumbel(F.col("id")))).first()[0] - 0.5772) < 0.05


def test_kth_largest(spark):
    keys = [random.Random(13).gauss(0, 1) for _ in range(500)] + [0.5] * 20
    df = spark.createDataFrame([(k,) for k in keys], "key double")
    for k in (1, 17, 200, 520):
        assert _kth_largest(df, k) == sorted(keys, reverse=True)[k - 1]
    assert _kth_largest(df.limit(0), 3) is None


def test_all_operators_are_registered():
    assert [any(n.startswith(f"op{i}_") for n in registry.QUERIES) for i in range(1, 11)] == [True] * 10


def test_decontamination_of_edited_items(spark):
    long = " ".join(f"w{chr(97 + i // 26)}{chr(97 + i % 26)}" for i in range(60))
    words = long.split()
    items = spark.createDataFrame(
        [(0, long), (1, "why does the old clock tower strike seven bells at noon"), (2, "Mary has 3 apples. John gives 4 more. Susan eats 2 now. Peter asks how many remain.")],
        "item_id long, text string",
    )
    rows = [
        (1, " ".join([*words[:30], "inserted", *words[30:]])),  # one word put in the middle
        (2, " ".join([*words[:30], *words[31:]])),  # one left out
        (3, "why does the old clock turret strike seven bells at noon"),  # one word changed in a short item
        (4, "Anna has 5 apples. Karl gives 6 more. Laura eats 7 now. Oscar asks how many remain."),  # names at the starts of sentences
        (5, " ".join(words[:20])),
        (6, "why does the new house stand empty at noon"),
        (7, "mary has 3 apples. john gives 4 more. susan eats 2 now. peter asks how many remain."),
    ]
    got = {(r["doc_id"], r["item_id"]) for r in contaminated(texts(docs_of(spark, rows)), items).collect()}
    assert got == {(1, 0), (2, 0), (3, 1), (4, 2), (7, 2)}


def test_warc_of_repeated_pages(spark):
    rows = [(i, f"http://host{i % 7}.example/{i}", f"page {i}") for i in range(700)] * 3 + [(None, "http://one.example/", "none")] * 1300 + [(9000, "http://blank.example/a\u00a0", "blank"), (9001, "http://blank.example/b\u3000", "blank")]
    got = archive_and_read(spark.createDataFrame(rows, "page_id long, url string, html string"))
    assert Counter(r["page_id"] for r in got.collect()) == Counter(i for i, _, _ in rows)


def test_decontamination_of_items_that_tell_little(spark):
    items = spark.createDataFrame([(0, "42"), (1, "the"), (2, "1, 2, 3, 4, 5, 6, 7, 8, 9"), (3, "What is 3 plus 4 in the old town hall?"), (4, "What is 5 plus 6 in the old town hall?")], "item_id long, text string")
    rows = [(1, "There are 42 of the kind, 43 of the other."), (2, "42"), (3, " The. "), (4, "9 8 7 6 5 4 3 2 1"), (5, "So: what is 3 plus 4 in the old town hall?"), (6, "1 2 3 4 5 6 7 8 9")]
    found = contaminated(texts(docs_of(spark, rows)), items)
    assert {(r["doc_id"], r["item_id"]) for r in found.collect()} == {(2, 0), (3, 1), (6, 2), (5, 3), (5, 4)}
    plan = found._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan
