"""Training-data operators against brute force on small tables with nulls, ties, repeats and odd texts."""

import hashlib
import random
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from cloudlattice.llm import ann, grid_join, html_extract, licenses, mixing, packing, sharding, shingle_join, suffix_dedup, suffix_doubling, toxicity
from cloudlattice.llm.graph import components

R = random.Random(4)
WORDS = ["".join(R.choice("abcdefghij") for _ in range(R.randint(2, 7))) for _ in range(3000)]


def prose(n):
    return " ".join(R.choice(WORDS) for _ in range(n))


@pytest.fixture(scope="module")
def rows():
    """Exact and near copies, shared passages, odd white space, empty, null and long texts, a repeated row."""
    passage, base = prose(90), prose(150)
    texts = [base, base, base.upper(), None, "", "  \n ", "one", "one two three", "ab " * 400, prose(4000)]
    for _ in range(12):
        w = base.split()
        for _ in range(R.randint(1, 5)):
            w[R.randrange(len(w))] = R.choice(WORDS)
        texts.append(" ".join(w))
    texts += [f"{prose(R.randint(5, 60))} {passage} {prose(R.randint(5, 60))}" for _ in range(15)]
    texts += [prose(R.randint(1, 300)) for _ in range(40)] + ["é" * 450 + "x", "é" * 450]
    out = [(k, t, "en", None if k % 9 == 0 else f"s{k % 4}", len(t or "")) for k, t in enumerate(texts)]
    return out + [out[12]]


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").repartition(3).cache()


@pytest.fixture(scope="module")
def none(docs):
    return docs.where("false")


def shingles(text):
    w = (text or "").encode().lower().split()
    return frozenset(tuple(w[k : k + 4]) for k in range(len(w) - 3)) if len(w) >= 4 else frozenset([tuple(w)] if w else [])


def test_shingle_classes(docs, rows, none):
    sets = [shingles(t) for _, t, *_ in rows]
    label = list(range(len(rows)))
    changed = True
    while changed:
        changed = False
        for a in range(len(rows)):
            for b in range(len(rows)):
                if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 85 * len(sets[a] | sets[b]) and label[a] != label[b]:
                    label[a] = label[b] = min(label[a], label[b])
                    changed = True
    want = sorted((r[0], len(s), min(q[0] for q, m in zip(rows, label) if m == k) if s else r[0]) for r, s, k in zip(rows, sets, label))
    assert sorted(map(tuple, shingle_join.classes(docs).collect())) == want
    assert shingle_join.classes(none).count() == 0
    assert shingle_join.representatives(docs).count() == len({w[2] for w in want})


def test_sketch_never_rules_out_a_link():
    rng = np.random.default_rng(1)
    for _ in range(200):
        a = np.unique(rng.integers(0, 1 << 62, rng.integers(5, 300)).astype(np.uint64))
        b = np.unique(np.concatenate([a[rng.random(len(a)) < 0.93], rng.integers(0, 1 << 62, rng.integers(0, 10)).astype(np.uint64)]))
        sketches = [np.frombuffer(shingle_join.parity_sketch(x), np.uint8) for x in (a, b)]
        if shingle_join.similar(a, b, 85):
            assert shingle_join.may_link(*sketches, len(a), len(b), 85)


def test_suffix_dedup(docs, rows, none):
    data = [(t or "").encode() for _, t, *_ in rows]
    count = Counter(d[k : k + 400] for d in data for k in range(len(d) - 399))
    want = []
    for (doc, *_), d in zip(rows, data):
        gone = np.zeros(len(d), bool)
        for k in range(len(d) - 399):
            if count[d[k : k + 400]] > 1:
                gone[k : k + 400] = True
        want.append((doc, int(gone.sum()), hashlib.sha256(bytes(np.frombuffer(d, np.uint8)[~gone])).hexdigest()))
    got = []
    for r in suffix_dedup.with_ranges(docs).collect():
        d, spans = (r["text"] or "").encode(), suffix_dedup.merged([(x["start"], x["end"]) for x in r["ranges"] or []])
        left = suffix_dedup.remaining(d, spans)
        got.append((r["doc_id"], len(d) - len(left), hashlib.sha256(left).hexdigest()))
    assert sorted(got) == sorted(want)
    assert suffix_dedup.with_ranges(none).count() == 0
    kept = suffix_dedup.deduplicated(docs)
    assert kept.columns == docs.columns and kept.count() == len(rows)


def test_plain_doubling_finds_the_same_ranges(docs, none):
    keyed = suffix_dedup.keyed(docs)

    def spans(ranges):
        found = {}
        for r in ranges.collect():
            found.setdefault((r["doc_id"], r["text_hash"]), []).append((r["start"], r["end"]))
        return {k: suffix_dedup.merged(v) for k, v in found.items()}

    for length in (100, 400):
        assert spans(suffix_doubling.covered(keyed, length)) == spans(suffix_dedup.covered(keyed, length))
    assert suffix_doubling.covered(suffix_dedup.keyed(none)).count() == 0


def test_sharding(docs, rows, none):
    got = sharding.shard_documents(docs, 5).collect()
    assert len(got) == len(rows)
    for s in range(5):
        mine = sorted(r["slot"] for r in got if r["shard"] == s)
        assert mine == list(range(len(mine)))
    of = {}
    text = {r[0]: r[1] for r in rows}
    for r in got:
        assert r["size"] == len((text[r["doc_id"]] or "").encode()) + 16
        assert r["text_crc32"] == zlib.crc32((text[r["doc_id"]] or "").encode())
        of.setdefault(text[r["doc_id"]] or "", set()).add(r["shard"])
    assert all(len(s) == 1 for s in of.values())
    assert sharding.shard_documents(none, 5).count() == 0


def test_lpt_by_hand():
    assert sharding.lpt([("a", 5), ("b", 4), ("c", 3), ("d", 3), ("e", 3)], 2) == {"a": 0, "b": 1, "c": 1, "d": 0, "e": 1}


def test_mixing(docs, rows, none):
    got = mixing.mix_documents(docs).collect()
    taken = lambda r: sum(d["words"] for d in r["draws"])
    assert len(got) == len(rows)
    source = Counter()
    for r in got:
        assert r["size"] == len((r["text"] or "").encode().split()) and taken(r) <= 3 * r["size"]
        source[r["source"]] += taken(r)
    for r in got:
        assert abs(source[r["source"]] - r["target"]) <= 0.5
    key = lambda rs: sorted((r["doc_id"], taken(r)) for r in rs)
    assert key(got) == key(mixing.mix_documents(docs.repartition(5)).collect())
    assert mixing.mix_documents(none).count() == 0
    assert mixing.mixed(docs).columns == docs.columns
    # the tree's shards: near-equal numbers of draws, and each shard whole in a partition of the mix
    drawn = Counter(d["shard"] for r in mixing.mix_documents(docs, shards=4).collect() for d in r["draws"])
    assert set(drawn) == set(range(4))
    placed = docs.withColumn("lang", F.monotonically_increasing_id().cast("string"))
    of = {(r["lang"], d["epoch"]): d["shard"] for r in mixing.mix_documents(placed, shards=4).collect() for d in r["draws"]}
    held = mixing.mixed(placed, shards=4).select("lang", F.spark_partition_id().alias("p")).collect()
    homes = {}
    for lang, n in Counter((r["lang"], r["p"]) for r in held).items():
        homes.setdefault(lang[0], set()).add(lang[1])
    parts = {}
    for lang, where in homes.items():
        shards = {s for (x, _), s in of.items() if x == lang}
        assert len(where) <= len(shards)
        if len(shards) == 1:
            parts.setdefault(shards.pop(), set()).update(where)
    assert all(len(p) == 1 for p in parts.values())


def test_targets_and_tree():
    assert mixing.capped_targets([10, 100, 0], [1, 1, 1], 110) == pytest.approx([30, 80, 0])
    dealt = mixing.split_quotas({0: 10, 1: 3, 3: 7}, 5, random.Random(0))
    assert sum(map(Counter, dealt), Counter()) == {0: 10, 1: 3, 3: 7}
    assert [sum(d.values()) for d in dealt] == [4] * 5


def test_packing(docs, rows, none):
    from tokenizers import Tokenizer

    path = packing.default_tokenizer()
    own = Tokenizer.from_file(path)
    ids = {r[0]: own.encode(r[1] or "", add_special_tokens=False).ids + [1] for r in rows}
    got = packing.pack_documents(docs, path).collect()
    whole, filled = Counter(), {}
    for r in got:
        part = ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert len(part) == r["length"] and r["doc_tokens"] == len(ids[r["doc_id"]])
        assert zlib.crc32(np.array(part, "<u4").tobytes()) == r["ids_crc32"]
        whole[r["doc_id"]] += r["length"]
        filled.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert whole == Counter(r[0] for r in rows for _ in ids[r[0]])
    for places in filled.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at
            at += length
        assert at <= 2048
    assert packing.pack_documents(none, path).count() == 0


def test_odd_texts_encode_like_the_tokenizer():
    from tokenizers import Tokenizer

    path = packing.default_tokenizer()
    own, mine = Tokenizer.from_file(path), packing.Encoder(path)
    for t in ["", " ", "a  b", "a\n\nb", "a \n b", " a", "b ", "²½ x1y2", "it's we'll", "日本 語　x", "tab\tx", "<|endoftext|> x", "a\x1cb", "é à\nü"]:
        assert np.frombuffer(mine(t), "<u4").tolist() == own.encode(t, add_special_tokens=False).ids


def test_differencing_levels():
    sizes = [R.randint(1, 900) for _ in range(300)]
    groups = packing.windows(sizes, 2048)
    assert sorted(i for g in groups for i in g) == list(range(300))
    assert max(sum(sizes[i] for i in g) for g in groups) <= 2048
    assert sum(sizes) / (2048 * len(groups)) > 0.97


def vectors(spark):
    rng = np.random.default_rng(2)
    base = rng.normal(size=(60, 16))
    near = base[rng.integers(0, 10, 200)] + rng.normal(scale=0.02, size=(200, 16))
    out = [(k, [float(np.float32(x)) for x in v], int(k % 3)) for k, v in enumerate(np.vstack([base, near, near[:5]]))]
    out += [(1000, None, 1), (1001, [0.0] * 16, 1), (1002, [float("nan")] * 16, 1), (1003, out[0][1], None), (1004, [None] + [1.0] * 15, 1)]
    return out, spark.createDataFrame(out, "vec_id long, embedding array<float>, label int")


def test_grid_join(spark):
    rows, table = vectors(spark)
    good = [(i, np.array(v, float), c) for i, v, c in rows if i < 1000]
    links, label = Counter(), {i: i for i, *_ in rows}
    unit = np.array([v / np.linalg.norm(v) for _, v, _ in good])
    dots = unit @ unit.T
    changed = True
    pairs = [(a, b) for a in range(len(good)) for b in range(len(good)) if a != b and good[a][2] == good[b][2] and dots[a, b] >= 0.98]
    for a, _ in pairs:
        links[good[a][0]] += 1
    while changed:
        changed = False
        for a, b in pairs:
            low = min(label[good[a][0]], label[good[b][0]])
            for k in (a, b):
                changed |= label[good[k][0]] != low
                label[good[k][0]] = low
    want = sorted((i, links[i], label[i], label[i] == i) for i, *_ in rows)
    assert sorted(map(tuple, grid_join.near_duplicates(table).collect())) == want
    assert grid_join.near_duplicates(table.where("false")).count() == 0


def test_search_recall(spark):
    rows, table = vectors(spark)
    got = ann.search(table, F.col("vec_id") % 10 == 0).collect()
    good = [(i, np.array(v, float)) for i, v, _ in rows if v and None not in v and np.isfinite(v).all() and np.any(v)]
    unit = np.array([v / np.linalg.norm(v) for _, v in good])
    hits = total = 0
    for q, (i, _) in enumerate(good):
        if i % 10 == 0:
            order = [good[k][0] for k in np.argsort(-(unit @ unit[q]), kind="stable") if k != q][:5]
            mine = [r["vec_id"] for r in sorted((r for r in got if r["query_id"] == i), key=lambda r: r["rank"])]
            hits, total = hits + len(set(order) & set(mine)), total + 5
    assert hits / total >= 0.9
    assert ann.search(table.where("false"), F.lit(True)).count() == 0


def test_html():
    page = "<html><head><title>t</title><script>var a='</p>'</script></head><body><nav><a href=x>Home</a></nav><div class=ad>buy</div><article><h1>A &amp; B</h1><p>one\n two<p>three <b>four</article><footer>&copy; me</footer>"
    assert html_extract.main_texts([page, None, "", "<p"]) == ["A & B\none two\nthree four", "", "", ""]


def test_labeller_gradient():
    from cloudlattice.llm import html_model, html_training

    x, y = html_training.examples(3, 5)
    p = html_model.initial(1)
    _, g = html_model.gradients(p, x, y)
    for name, at in (("wf", (3, 7)), ("ub", (2, 11)), ("out", (5,)), ("cf", (4,))):
        old = p[name][at]
        loss = []
        for step in (1e-5, -1e-5):
            p[name][at] = old + step
            loss.append(html_model.gradients(p, x, y)[0])
        p[name][at] = old
        assert (loss[0] - loss[1]) / 2e-5 == pytest.approx(g[name][at], rel=1e-3, abs=1e-7)


def test_licenses(spark):
    texts = [(1, "Intro words here. Licensed under the Apache License, Version 2.0. More text follows it."), (2, None), (3, ""), (4, "released under the mit license"), (5, "Released under the old License."), (6, prose(500) + " Licensed under CC BY-NC 4.0. " + prose(500))]
    got = licenses.scan(spark.createDataFrame(texts, "doc_id long, text string"))
    assert sorted((r["doc_id"], r["license"]) for r in got.collect()) == [(1, "Apache-2.0"), (4, "MIT"), (6, "CC-BY-NC-4.0")]


def test_whole_license_texts_come_through_the_bands(spark, monkeypatch):
    rows, want = [], []
    for k, (name, text) in enumerate(licenses.TEMPLATES):
        w = text.split()
        if len(w) > 40:
            w[len(w) // 2] = "changed"
        rows += [(k, f"{prose(R.randint(0, 700))} {' '.join(w)} {prose(R.randint(0, 700))}", "x", "y"), (100 + k, " ".join(w[: len(w) // 2]), "x", "y")]
        want.append((k, name))
    rows += [rows[0], (None, rows[2][1], "x", "y"), (900, None, "x", "y"), (901, "", "x", "y")]
    table = spark.createDataFrame(rows, "doc_id int, text string, class string, window string")
    found = {(r["doc_id"], r["license"]) for r in licenses.scan(table).collect()}
    assert set(want) <= found and {(d, n) for d, n in found if d is not None and d >= 100} <= {(100 + k, n) for k, n in want}
    assert licenses.scan(table.where("false")).count() == 0
    # without equal minima nothing is retrieved: rows come through the bands alone
    own = licenses.catalogue(spark).withColumn("minima", F.transform("minima", lambda x: x + 1))
    monkeypatch.setattr(licenses, "catalogue", lambda *_: own)
    assert licenses.scan(table).count() == 0


def test_toxicity(spark):
    bad = ["grobbel", "snarfle", "vexnot"]
    rows = []
    for k in range(600):
        w = prose(60).split()
        if k % 5 == 0:
            for _ in range(5):
                w.insert(R.randrange(len(w)), R.choice(bad))
        rows.append((k, " ".join(w), int(k % 5 == 0)))
    rows += [(700, None, 0), (701, "", 0)]
    df = spark.createDataFrame(rows, "doc_id long, text string, toxic int")
    model = toxicity.fit(df, df.select("doc_id", "toxic"))
    got = toxicity.score_documents(df.select("doc_id", "text"), model).collect()
    held = [r for r in got if zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2]
    right = [(r["toxicity"] >= 0.3) == (r["doc_id"] % 5 == 0 and r["doc_id"] < 700) for r in held]
    assert np.mean(right) > 0.9 and all(0 <= r["toxicity"] <= 1 for r in got)


def test_components_of_a_chain_and_a_star(spark):
    edges = [(k, k + 1) for k in range(50)] + [(100, 100 + k) for k in range(1, 40)]
    got = dict(map(tuple, components(spark.createDataFrame(edges, "u long, v long")).collect()))
    assert got == {k: 0 for k in range(51)} | {100 + k: 100 for k in range(40)}
