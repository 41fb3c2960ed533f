"""Registered queries on the whole small tables, against plain Python."""

import base64
import hashlib
import struct

import numpy as np
import public_tokenizers as P
import tiktoken
import xxhash
from tokenizers import Tokenizer

from hubloom.llm import registry
from hubloom.llm.common import table
from hubloom.llm.syncmers import KEPT, K, _points, anchors, likeness, sketch_many


def documents(spark, sf_dir):
    return {r["doc_id"]: r["text"] or "" for r in table(spark, sf_dir, "documents").select("doc_id", "text").collect()}


def answers(spark, sf_dir, name):
    got = registry.QUERIES[name](spark, sf_dir).collect()
    by = {r["doc_id"]: r for r in got}
    assert len(by) == len(got)
    return by


def test_byte_bpe(spark, sf_dir):
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(P.path("byte_bpe_multi_50k.tiktoken"), "rb"))}
    library = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    docs, got = documents(spark, sf_dir), answers(spark, sf_dir, "op1_byte_bpe")
    assert set(got) == set(docs)
    for i, text in docs.items():
        ids = library.encode_ordinary(text)
        assert (got[i]["n_tokens"], got[i]["ids_sha256"]) == (len(ids), hashlib.sha256(struct.pack(f"<{len(ids)}I", *ids)).hexdigest())
        assert got[i]["decoded_sha256"] == hashlib.sha256(text.encode()).hexdigest()


def test_token_counts(spark, sf_dir):
    docs, got = documents(spark, sf_dir), answers(spark, sf_dir, "op7_token_counts")
    own = Tokenizer.from_file(P.path("word_bpe_49k.json"))
    own.no_truncation()
    own.no_padding()
    for i, text in docs.items():
        n = len(own.encode(text, add_special_tokens=False).ids)
        assert (got[i]["n_bytes"], got[i]["n_tokens"], got[i]["over_limit"]) == (len(text.encode()), n, n > 2048)


def test_run_index(spark, sf_dir):
    docs, got = documents(spark, sf_dir), answers(spark, sf_dir, "op4_run_index")
    first: dict[bytes, int] = {}
    for i in sorted(docs):
        raw = docs[i].encode()
        gone = bytearray(len(raw))
        for j in range(len(raw) - 49):
            if first.setdefault(raw[j : j + 50], i) < i:
                gone[j : j + 50] = b"\1" * 50
        spans = sum(1 for j, g in enumerate(gone) if g and (j == 0 or not gone[j - 1]))
        kept = hashlib.sha256(bytes(c for c, g in zip(raw, gone, strict=True) if not g)).hexdigest()
        assert tuple(got[i])[1:] == (len(raw), sum(gone), spans, kept)


def test_simhash(spark, sf_dir):
    docs, got = documents(spark, sf_dir), answers(spark, sf_dir, "op6_simhash")
    prints = {}
    for i, text in docs.items():
        words = text.encode().lower().split()
        shingles = [b" ".join(words[j : j + 4]) for j in range(max(1, len(words) - 3))] if words else []
        h = [xxhash.xxh64_intdigest(s, 42) for s in shingles]
        prints[i] = sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))
        assert got[i]["fingerprint"] == f"{prints[i]:016x}"
    root = {i: i for i in docs}
    for _ in range(len(docs)):
        before = dict(root)
        for a in docs:
            root[a] = min(root[b] for b in docs if (prints[a] ^ prints[b]).bit_count() <= 4)
        if root == before:
            break
    assert {i: r["component_id"] for i, r in got.items()} == root


def test_syncmers_of_documents(spark, sf_dir):
    docs, got = documents(spark, sf_dir), answers(spark, sf_dir, "op9_syncmers")
    order = sorted(docs)
    for at, i in enumerate(order):
        text, follower = docs[i], docs[order[(at + 1) % len(order)]]
        n = len(text) // 4
        changed = text[: len(text) - n] + follower[:n]
        own, theirs, next_one = sketch_many([text, changed, follower])
        assert (got[i]["n_chars"], got[i]["edited_sha256"]) == (len(text), hashlib.sha256(changed.encode()).hexdigest())
        assert (got[i]["near_edited"], got[i]["near_next"]) == (likeness(own, theirs), likeness(own, next_one))
    # Anchors one k-mer at a time: whether a k-mer is one depends on nothing around it; the least hashes are kept.
    for i in order[:12]:
        points = _points(docs[i][:3000])
        h, where = anchors(points)
        alone = [(j, int(a[0])) for j in range(len(points) - K + 1) for a, _ in [anchors(points[j : j + K])] if len(a)]
        assert alone == list(zip(where.tolist(), h.tolist(), strict=True))
        kept = sorted({x >> 32 for _, x in alone})[:KEPT]
        assert sketch_many([docs[i][:3000]])[0][0].tolist() == kept


def test_katz(spark, sf_dir):
    got = answers(spark, sf_dir, "op5_katz")
    docs = documents(spark, sf_dir)
    assert set(got) == set(docs) and all(r["n_tokens"] == len(docs[i].encode().lower().split()) + 1 for i, r in got.items())
    held = [r for r in got.values() if r["held_out"]]
    assert 0 < len(held) < len(got)
    # The model reads context, so held-out texts are likelier than by single words.
    assert sum(r["score"] for r in held) > sum(r["base_score"] for r in held)
    assert np.isfinite([r["score"] for r in got.values()]).all()
