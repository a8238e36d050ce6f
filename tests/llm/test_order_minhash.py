"""Signatures and likeness against plain loops over the same hashes, and what they say about edits."""

import random
import re

import xxhash

from spark_curation.llm import order_minhash as om

DOCS = "doc_id long, text string"


def chain(*parts):
    """The engine's hash of several values: each one's hash is the next one's seed."""
    h = 42
    for p in parts:
        raw = p.encode() if isinstance(p, str) else p
        h = xxhash.xxh64(raw, seed=h).intdigest()
    return h


def signature(text):
    ws = [w for w in re.split(rf"\s+|(?<={om.UNSPACED})|(?={om.UNSPACED})", text or "") if w]
    kmers = [ws[i : i + om.K] for i in range(len(ws) - om.K + 1)] if len(ws) >= om.K else [[" ".join(ws)]] if ws else []
    seen, bins = {}, {}
    for at, k in enumerate(kmers):
        h = chain(*k) & ((1 << 63 - om.POS) - 1)
        n = seen[h] = seen.get(h, -1) + 1
        g = chain(h.to_bytes(8, "little"), n.to_bytes(4, "little")) >> om.POS
        bins.setdefault(g >> om.RANK & 63, []).append((g & (1 << om.RANK) - 1, at))
    out = {}
    for b, few in bins.items():
        ranks = [r for r, _ in sorted(sorted(few)[: om.TUPLE], key=lambda x: x[1])]
        out[b] = chain(*(r.to_bytes(8, "little") for r in ranks)) & 0xFFFFFFFF
    return out


def test_fingerprints_equal_plain_loops(spark):
    r = random.Random(6)
    some = lambda n, v: " ".join(r.choice([f"w{r.randrange(v)}", "é", "日本語", "x"]) for _ in range(n))
    rows = [(i, some(r.choice([0, 1, 2, 3, 5, 40, 400]), r.choice([3, 50, 5000]))) for i in range(60)] + [(60, None), (61, "a b " * 700)]
    got = {x.doc_id: x for x in om.fingerprints(spark.createDataFrame(rows, DOCS)).collect()}
    texts = [t or "" for _, t in rows]
    for i, t in rows:
        t, after = t or "", texts[(i + 1) % len(rows)]
        half = len(t) // 2
        edited = t[: len(t) - half] + after[:half]
        a, b, c = signature(t), signature(edited), signature(after)
        assert got[i].fingerprint == "".join(f"{k:02x}{v & 0xFFFF:04x}" for k, v in sorted(a.items()))
        for other, value in ((b, got[i].near_edited), (c, got[i].near_next)):
            every = a.keys() | other.keys()
            want = (sum(a.get(k) == other.get(k) for k in every) / len(every)) ** (1 / om.TUPLE) if every else 1.0
            assert abs(value - want) < 1e-9


def test_order_counts(spark):
    r = random.Random(1)
    parts = [" ".join(f"w{r.randrange(10**6)}" for _ in range(100)) for _ in range(8)]
    moved = parts[:]
    r.shuffle(moved)
    edited = " ".join(parts).split()
    for at in r.sample(range(800), 40):
        edited[at] = "new"
    rows = [(1, " ".join(parts)), (2, " ".join(edited)), (3, " ".join(moved)), (4, " ".join(moved))]
    got = {x.doc_id: x for x in om.fingerprints(spark.createDataFrame(rows, DOCS)).collect()}
    assert got[1].near_next > 0.6 and got[3].near_next == 1.0 and got[2].near_next < got[1].near_next
