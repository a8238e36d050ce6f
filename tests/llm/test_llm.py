"""The ten operators and the pipeline: brute force, round trips, held-out accuracy, and odd inputs."""

import hashlib
import random
import re

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

import corpus_pipeline
from spark_curation.io import table
from spark_curation.llm import decontamination, graph, licences, order_minhash, passages, pieces, pii, quality, queries, shingling, simhash
from tests.conftest import DATA

DOCS = "doc_id long, text string"
ODD = [(1, None), (2, ""), (3, " \n\t "), (4, "word"), (5, "word"), (6, "日本語 テキスト 𠀀"), (7, "a\x00b ﬀ ▁ x"), (None, "no id here at all"), (8, "one two three four five " * 4000), (9, "x" * 50_000)]


@pytest.fixture(scope="module")
def odd(spark):
    extra = spark.createDataFrame([(i, t, "clash", 1.0) for i, t in ODD], DOCS + ", component_id string, row double")
    return extra


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


def test_odd_inputs_keep_every_row(spark, odd, empty):
    model = pieces.tokenizer_path()
    item = spark.createDataFrame([(1, "one two three four five one two"), (2, None), (3, ""), (None, "x")], "item_id long, text string")
    whole = {
        "quality": lambda d: quality.classify(d), "pieces": lambda d: pieces.digests(pieces.encode_documents(d, model)), "licences": licences.scan,
        "simhash": simhash.near_duplicates, "pii": lambda d: pii.digests(pii.find(d)), "order": order_minhash.fingerprints,
    }
    for name, f in whole.items():
        assert f(odd).count() == len(ODD), name
        assert f(empty).count() == 0, name
    hits = decontamination.search(odd, item).collect()
    assert {(h.doc_id, h.item_id) for h in hits} == {(8, 1)}
    assert decontamination.search(empty, item).count() == 0
    assert decontamination.search(odd, item.where("false")).count() == 0
    assert {r.doc_id for r in passages.repeated(odd).collect()} == set(range(1, 10))
    for f in (quality.keep_good, simhash.keep_one, pii.redact_documents, lambda d: decontamination.keep_clean(d, item)):
        assert f(odd).columns == odd.columns and f(empty).count() == 0


def brute_simhash(text):
    low = re.sub("[A-Z]", lambda m: m[0].lower(), text or "")
    ws = re.findall(r"[^\x20\x09-\x0D]+", low)
    if not ws:
        return 0
    sh = [" ".join(ws[i : i + 4]) for i in range(max(1, len(ws) - 3))]
    h = [xxhash.xxh64(s.encode(), seed=42).intdigest() for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_simhash_against_brute_force(spark):
    r = random.Random(2)
    base = [" ".join(r.choice(["Alpha", "beta", "gamma", "Dé", "x"]) + str(r.randrange(90)) for _ in range(60)) for _ in range(12)]
    rows = []
    for i in range(80):
        ws = r.choice(base).split()
        for _ in range(r.choice([0, 0, 1, 1, 2])):
            ws[r.randrange(len(ws))] = "edited" + str(r.randrange(9))
        rows.append((i, " ".join(ws)))
    rows += [(90, None), (91, ""), (92, " \n")]
    got = {x.doc_id: x for x in simhash.near_duplicates(spark.createDataFrame(rows, DOCS)).collect()}
    fps = {i: brute_simhash(t) for i, t in rows}
    assert {i: x.fingerprint for i, x in got.items()} == {i: f"{f:016x}" for i, f in fps.items()}
    comp = {i: i for i in fps}
    for _ in fps:
        for a in fps:
            for b in fps:
                if (fps[a] ^ fps[b]).bit_count() <= 4:
                    comp[a] = comp[b] = min(comp[a], comp[b])
    assert {i: x.component_id for i, x in got.items()} == comp
    kept = simhash.keep_one(spark.createDataFrame(rows + rows[:5], DOCS)).collect()
    assert sorted(x.doc_id for x in kept) == sorted(set(comp.values()))


def test_links_for_any_distance_and_hubs(spark):
    r = random.Random(4)
    centre = r.getrandbits(64)
    fps = {centre ^ sum(1 << b for b in r.sample(range(64), r.randrange(7))) for _ in range(150)} | {r.getrandbits(64) for _ in range(50)}
    df = spark.createDataFrame([(f - (1 << 64) if f >> 63 else f,) for f in fps], "fp long")
    for distance in (1, 3, 4):
        got = {tuple(sorted((x.u % (1 << 64), x.v % (1 << 64)))) for x in simhash.links(df, distance).collect()}
        assert got == {(a, b) for a in fps for b in fps if a < b and (a ^ b).bit_count() <= distance}


def test_components_of_long_paths_and_stars(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, i) for i in range(101, 160)] + [(7, 7), (300, 200)]
    got = {r.node: r.component for r in graph.components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert got == dict.fromkeys(range(41), 0) | dict.fromkeys(range(100, 160), 100) | {200: 200, 300: 200}
    assert graph.components(spark.createDataFrame([], "u long, v long")).count() == 0


def test_pieces_equal_the_library_and_spans_cover_the_source(spark):
    with open(pieces.tokenizer_path(), "rb") as f:
        enc = pieces.Encoder(f.read())
    r = random.Random(1)
    texts = ["", " ", "  a  b ", "a▁b", "日本 𠀀\n\n", "<s> </s>", "a\x00b"] + ["".join(r.choice(" \n▁abé日.,0") for _ in range(r.randrange(30))) for _ in range(300)]
    for text, ids, back in zip(texts, got := enc.encode(texts), enc.decode(got), strict=True):
        assert ids.tolist() == enc.library.encode(text, add_bos=True, add_eos=True) and back == enc.library.decode(ids.tolist())
        begin, end = enc.spans(text, ids)
        raw = text.encode()
        assert b"".join(raw[a:b] for a, b in zip(begin, end, strict=True)) == raw
        assert (begin[1:] == end[:-1]).all()


def test_compiled_map_takes_the_longest_prefix():
    """A small double array built here by hand: 'a' -> 'x', 'ab' -> 'yz'."""
    units = np.zeros(1024, np.uint32)

    def place(node_offset, label, child_offset, leaf):
        units[node_offset ^ label] = label | (child_offset ^ (node_offset ^ label)) << 10 | (0x100 if leaf is not None else 0)
        if leaf is not None:
            units[child_offset] = leaf | 0x80000000

    units[0] = 256 << 10
    place(256, ord("a"), 512, 0)
    place(512, ord("b"), 768, 2)
    blob = (units.nbytes).to_bytes(4, "little") + units.tobytes() + b"x\0yz\0"
    got, origin = pieces.CharMap(blob).apply(b"cabaa")
    assert got == b"cyzxx" and origin.tolist() == [0, 1, 1, 3, 4, 5]


def test_containment_equals_brute_force(spark):
    docs, bench = table(spark, DATA, "documents"), table(spark, DATA, "benchmark")
    want = set()
    texts = [(d.doc_id, shingling.words(d.text)) for d in docs.collect()]
    for b in bench.collect():
        q = set(shingling.shingles(shingling.words(b.text), 5))
        want |= {(i, b.item_id) for i, ws in texts if len(q & set(shingling.shingles(ws, 5))) >= 0.8 * len(q)}
    got = {(r.doc_id, r.item_id) for r in decontamination.search(docs, bench).collect()}
    assert got == want and want
    joined = decontamination.search(docs, bench, held=0)
    assert sorted(joined.collect()) == sorted(decontamination.search(docs, bench).collect())
    for held in (0, decontamination.HELD):
        assert decontamination.keep_clean(docs, bench, held=held).count() == docs.count() - len({d for d, _ in want})


def test_near_copies_of_items_count(spark):
    ws = [f"w{i}" for i in range(40)]
    changed = ws[:39] + ["other"]
    docs = spark.createDataFrame([(1, "pre " * 500 + " ".join(changed) + " post" * 500), (2, " ".join(ws[:25])), (3, "A b")], DOCS)
    bench = spark.createDataFrame([(7, " ".join(ws)), (8, "a B")], "item_id long, text string")
    for held in (0, decontamination.HELD):
        assert {(r.doc_id, r.item_id) for r in decontamination.search(docs, bench, held=held).collect()} == {(1, 7), (3, 8)}


def test_containment_at_other_sizes_and_thresholds(spark):
    """Scattered shingles, items of 1 to 200 words, against all pairs, by index and by join."""
    r = random.Random(12)
    pool = [f"p{i}" for i in range(60)]
    some = lambda n: " ".join(r.choice(pool) for _ in range(n))
    items = [(i, some(r.choice([1, 2, 4, 5, 6, 9, 20, 200]))) for i in range(40)]
    docs = [(i, " ".join(some(r.randrange(40)) + " " + (t if r.random() < 0.6 else t[: len(t) * 3 // 4]) for t in r.sample([t for _, t in items], 2))) for i in range(60)]
    docs += [docs[0], (None, docs[1][1]), (99, None)]
    sh = lambda ws, w: {tuple(ws[i : i + w]) for i in range(len(ws) - w + 1)}
    d, b = spark.createDataFrame(docs, DOCS), spark.createDataFrame(items, "item_id long, text string")
    for threshold in (0.5, 0.8, 1.0):
        want = []
        for k, t in docs:
            for i, x in items:
                w = min(5, len(x.split()))
                q = sh(x.split(), w)
                n = len(q & sh((t or "").split(), w))
                want += [(k, i, len(q), n)] if n >= threshold * len(q) - 1e-9 else []
        for held in (0, decontamination.HELD):
            got = [tuple(x)[:4] for x in decontamination.search(d, b, held=held, threshold=threshold).collect()]
            assert sorted(got, key=str) == sorted(want, key=str) and want
            clean = decontamination.keep_clean(d, b, held=held, threshold=threshold)
            assert sorted(map(str, clean.collect())) == sorted(str(x) for x in d.collect() if not any(w[0] == x.doc_id for w in want))


def test_licences_equal_plain_search(spark):
    import duckdb

    rows = [(1, "Released under the MIT License. Under the mit license"), (2, "Licensed under CC BY-NC 4.0; apache license, version 2.0"), (3, "mit the under license"), (4, None), (5, "under the Émit license under the MIT licenses")]
    got = sorted(map(tuple, licences.scan(spark.createDataFrame(rows, DOCS)).collect()))
    c = duckdb.connect()
    c.sql("CREATE TABLE documents (doc_id BIGINT, text VARCHAR)")
    c.executemany("INSERT INTO documents VALUES (?, ?)", rows)
    assert got == sorted(c.sql(licences.oracle_sql()).fetchall())
    assert got[0][2:7] == (2, 1, 5, "mit", "mit") and got[1][5] == "apache-2,cc-by-nc" and got[2][2] == 0


def test_hundreds_of_templates(spark):
    """Random phrases that share words, against plain search; the plan does not grow with their number."""
    r = random.Random(5)
    ws = [f"w{i}" for i in range(30)]
    some = lambda a, b: [r.choice(ws) for _ in range(r.randrange(a, b))]
    made = [licences.Template(f"base{i}", " ".join(some(2, 4)), "", True) for i in range(3)]
    for i in range(400):
        text = some(3, 12)
        at = r.randrange(len(text))
        made.append(licences.Template(f"l{i % 50}", " ".join(text), " ".join(text[at : at + r.randrange(1, 5)])))
    rows = [(i, " ".join(some(0, 60))) for i in range(60)] + [(100, made[50].text.upper()), (101, None), (None, made[60].text + "," + made[60].text)]
    got = {x.doc_id: x for x in licences.scan(spark.createDataFrame(rows, DOCS), tuple(made)).collect()}
    for i, text in rows:
        w = re.findall(r"[a-z0-9]+", (text or "").lower())
        hits = [(t, s) for t in made for s in range(len(w)) if w[s : s + len(t.key_words)] == t.key_words]
        base = [s for t, s in hits if t.base]
        share = [sum(0 <= s - t.offset + j < len(w) and w[s - t.offset + j] == x for j, x in enumerate(t.words)) / len(t.words) for t, s in hits]
        x = got[i]
        assert (x.n_words, x.n_base, x.first_word, x.last_word) == (len(w), len(base), min(base, default=None), max(base, default=None))
        assert x.labels == ",".join(sorted({t.label for t, _ in hits})) and abs(x.score - max(share, default=0)) < 1e-9
    size = lambda ts: licences.scan(spark.createDataFrame(rows, DOCS), tuple(ts))._jdf.queryExecution().optimizedPlan().expressions().size()
    assert size(made) == size(made[:10])


def luhn(d):
    t = 0
    for i, c in enumerate(reversed(d)):
        x = int(c) * (1 + i % 2)
        t += x - 9 if x > 9 else x
    return t % 10 == 0


def brute_pii(text):
    pats = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20\-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}
    out = []
    for k, p in pats.items():
        for m in re.finditer(p, text or ""):
            v, d = m[0], re.sub("[^0-9]", "", m[0])
            if {"email": True, "ip": k == "ip" and all(int(x) <= 255 for x in v.split(".")), "card": 13 <= len(d) <= 19 and luhn(d), "phone": 9 <= len(d) <= 15}[k]:
                out.append(f"{k}:{m.start()}:{m.end()}")
    return ",".join(out)


def test_base_spans_equal_plain_search(spark):
    r = random.Random(3)
    bits = ["a@b.c", "@", ".com", "x_", "+1 (234) 555-1234", " ", "4111 1111 1111 1111", "1.2.3.4", ".", "-", "256", "日", "𠀀", "5500-0000-0000-0004", "12", "+", "\n", "password=abc123def456", "1.2.3.4.5.6.7.8", "a@b@c.d"]
    rows = [(i, "".join(r.choice(bits) for _ in range(r.randrange(0, 25)))) for i in range(500)] + [(900, "x@y.zz " * 300)]
    got = {x.doc_id: x for x in pii.digests(pii.find(spark.createDataFrame(rows, DOCS))).collect()}
    for i, t in rows:
        base = brute_pii(t)
        assert got[i].base_sha256 == hashlib.sha256(base.encode()).hexdigest()
        assert set(filter(None, base.split(","))) <= set(got[i].spans.split(","))
    red = {x.doc_id: x.text for x in pii.redact_documents(spark.createDataFrame([(1, "Mail a@b.com or call +1 (234) 555-1234."), (2, "clean")], DOCS)).collect()}
    assert red == {1: "Mail <email> or call <phone>.", 2: "clean"}


def test_order_minhash(spark):
    r = random.Random(6)
    text = lambda: " ".join(f"w{r.randrange(400)}" for _ in range(200))
    rows = [(i, text()) for i in range(30)]
    rows[7] = (7, rows[6][1])
    got = {x.doc_id: x for x in order_minhash.fingerprints(spark.createDataFrame(rows, DOCS)).collect()}
    for i, t in rows:
        after = rows[(i + 1) % 30][1]
        half = len(t) // 2
        want = t[: len(t) - half] + after[:half]
        assert got[i].edited_sha256 == hashlib.sha256(want.encode()).hexdigest() and got[i].n_chars == len(t)
    assert got[6].near_next == 1.0 and got[6].fingerprint == got[7].fingerprint
    near = [x.near_edited for i, x in got.items() if i != 6]
    assert min(near) > 0.1 and max(x.near_next for i, x in got.items() if i != 6) < 0.2
    one = spark.createDataFrame([(1, rows[0][1] + " " + rows[1][1]), (2, rows[1][1] + " " + rows[0][1])], DOCS)
    moved = order_minhash.fingerprints(one).where("doc_id = 1").first().near_next
    assert moved < 1.0


def test_next_document_over_bucket_edges(spark):
    rows = [(i * 3, f"t{i}", [i]) for i in range(100)]
    df = spark.createDataFrame(rows, "doc_id long, text string, sig array<long>")
    got = {x.doc_id: x.next_text for x in order_minhash.with_next(df, ["text", "sig"], per_bucket=7).collect()}
    assert got == {i * 3: f"t{(i + 1) % 100}" for i in range(100)}


def test_one_of_each_with_null_and_shared_ids(spark):
    r = random.Random(3)
    a, b, c, d, e = (" ".join(f"u{r.randrange(9999)}" for _ in range(60)) for _ in range(5))
    rows = [(1, a), (1, a), (None, a), (2, a), (None, b), (None, b), (None, c), (7, d), (7, e)]
    got = simhash.keep_one(spark.createDataFrame(rows, DOCS)).collect()
    assert sorted(map(str, got)) == sorted(map(str, spark.createDataFrame([(1, a), (None, b), (None, b), (None, c), (7, d), (7, e)], DOCS).collect()))


def test_hot_fingerprints_and_clashing_names(spark):
    rows = [(i, "the same words in every row of this table") for i in range(3000)] + [(5000 + i, f"t{i} u{i * 7} v{i * 13} w{i * 17} x{i * 19}") for i in range(50)]
    df = spark.createDataFrame([(*r, 1, 2, 3, "c") for r in rows], DOCS + ", stays int, print int, of_print int, fp string")
    got = simhash.near_duplicates(df)
    assert got.where("doc_id < 3000").select("component_id").distinct().collect() == [(0,)] and got.count() == len(rows)
    kept = simhash.keep_one(df.union(df.limit(1)))
    assert kept.columns == df.columns and kept.where("doc_id < 3000").count() == 1 and simhash.keep_one(df).where("doc_id < 3000").count() == 1


def test_items_that_share_an_id_or_have_none(spark):
    texts = [" ".join(f"{k}{i}" for i in range(12)) for k in "abcd"]
    docs = spark.createDataFrame([(i, f"x {t} y") for i, t in enumerate(texts)], DOCS)
    items = spark.createDataFrame([(0, texts[0]), (0, texts[1]), (None, texts[2])], "item_id long, text string")
    for held in (0, decontamination.HELD):
        assert sorted(r.doc_id for r in decontamination.search(docs, items, held=held).collect()) == [0, 1]
        assert [r.doc_id for r in decontamination.keep_clean(docs, items, held=held).collect()] == [3]


def test_quality_on_labels(spark):
    docs, labels = table(spark, "/root/testdata/sf0.01", "documents"), table(spark, "/root/testdata/sf0.01", "labels")
    rows = quality.classify(docs).join(labels, "doc_id").select("keep", "quality").collect()
    good, bad = [r.keep for r in rows if r.quality == 1], [r.keep for r in rows if r.quality == 0]
    assert sum(good) >= 0.99 * len(good) and sum(bad) <= 0.1 * len(bad)


def test_quality_depends_on_the_texts_alone(spark):
    docs = table(spark, DATA, "documents").select("doc_id", "text")
    plain = {r.doc_id: r.score for r in quality.classify(docs, sample=8).collect()}
    more = docs.withColumn("x", F.create_map(F.lit("a"), F.lit(1))).withColumn("votes", F.lit("clash")).repartition(7)
    assert {r.doc_id: r.score for r in quality.classify(more, sample=8).collect()} == plain
    assert quality.keep_good(more, sample=8).columns == more.columns


def test_quality_of_many_equal_rows(spark):
    good = [r.text for r in table(spark, DATA, "documents").join(table(spark, DATA, "labels"), "doc_id").where("quality = 1").collect()]
    rows = [(i, "BUY!! now### now### CHEAP!! deal### | x | y | z | now### now###") for i in range(4000)] + [(5000 + i, t) for i, t in enumerate(good)]
    got = quality.classify(spark.createDataFrame(rows, DOCS)).groupBy((F.col("doc_id") < 5000).alias("junk"), "keep").count().collect()
    assert {(r.junk, r.keep): r["count"] for r in got}[True, False] == 4000
    assert sum(r["count"] for r in got if not r.junk and r.keep) >= 0.98 * len(good)


def test_labeller_model_against_plain_loops():
    """Expectation-maximisation over patterns equals the same rounds row by row."""
    rng = random.Random(1)
    rows = ["".join(rng.choice("01-") if rng.random() < 0.4 else "1" for _ in quality.LABELLERS) for _ in range(300)]
    post, rates = quality.fit_labellers({p: rows.count(p) for p in set(rows)}, rounds=5)
    q = [0.1 if "0" in r else 0.9 for r in rows]
    for _ in range(5):
        rate = []
        for side in (q, [1 - x for x in q]):
            rate.append([min(max((1 + sum(w for r, w in zip(rows, side) if r[j] == "1")) / (2 + sum(w for r, w in zip(rows, side) if r[j] in "01")), 5e-4), 1 - 5e-4) for j in range(len(quality.LABELLERS))])
        rate[0] = [max(x, 1 - quality.FALSE_ALARM) if j < quality.ALARMS else x for j, x in enumerate(rate[0])]
        rate[1] = [min(a, b) for a, b in zip(rate[1], rate[0])]
        prior = min(max((8 + sum(q)) / (10 + len(q)), 0.05), 0.95)
        odds = []
        for r in rows:
            like = [prior, 1 - prior]
            for k in (0, 1):
                for j, c in enumerate(r):
                    like[k] *= {"1": rate[k][j], "0": 1 - rate[k][j], "-": 1}[c]
            odds.append(like[0] / sum(like))
        q = odds
    assert np.allclose([post[r] for r in rows], q) and np.allclose(rates.T, rate)


def test_pipeline_against_its_operators(spark):
    docs, bench = table(spark, DATA, "documents"), table(spark, DATA, "benchmark")
    good = {r.doc_id for r in quality.classify(docs).where("keep").collect()}
    left = docs.where(F.col("doc_id").isin(sorted(good)))
    one = {r.doc_id for r in simhash.near_duplicates(left).collect() if r.doc_id == r.component_id}
    dirty = {r.doc_id for r in decontamination.search(docs, bench).collect()}
    out = corpus_pipeline.run(spark, DATA).collect()
    assert {r.doc_id for r in out} == one - dirty and len(out) == len({r.doc_id for r in out})
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality", "near_duplicates", "decontamination", "pii", "tokens"]
    assert all(len(r.ids) == 4 * r.n_tokens for r in out)


def test_registry_has_one_query_for_each_operator():
    names = list(queries.QUERIES)
    assert [sum(n.startswith(f"op{i}_") for n in names) for i in range(1, 11)] == [1] * 10 and "pipeline" in names
