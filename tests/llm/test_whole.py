"""Inputs that a cap, a prefix or an assumption about the data once cut short."""

import zlib

import numpy as np
from pyspark.sql import functions as F

from cloudlattice.llm import ann, grid_join, html_extract, packing


def by_hand(rows, query, top=5):
    """(rank, vec_id) of the nearest rows of the query's length, ties to the smaller id."""
    v = dict(rows)
    q = np.array(v[query], np.float32).astype(float)
    found = []
    for i, x in rows:
        x = np.array(x, np.float32).astype(float)
        if i != query and len(x) == len(q):
            found.append((-float(ann.cosine(q[None], x[None])[0]), i))
    return [i for _, i in sorted(found)[:top]]


def nearest(spark, rows, queries):
    table = spark.createDataFrame([(i, [float(c) for c in x]) for i, x in rows], "vec_id long, embedding array<float>").repartition(1)
    got = ann.search(table, F.col("vec_id").isin(queries)).collect()
    return {q: [r["vec_id"] for r in sorted((r for r in got if r["query_id"] == q), key=lambda r: r["rank"])] for q in queries}


def test_search_among_thousands_of_copies(spark):
    rng = np.random.default_rng(5)
    same, close = rng.normal(size=(2, 16))
    rows = [(int(k), same) for k in rng.permutation(3000)]
    rows += [(3000 + k, x) for k, x in enumerate(close + rng.normal(scale=1e-3, size=(3000, 16)))]
    rows += [(6000 + k, x) for k, x in enumerate(rng.normal(size=(500, 16)))]
    queries = [0, 7, 2999, 3000, 4500, 6000, 6100]
    got = nearest(spark, rows, queries)
    assert got[2999] == [0, 1, 2, 3, 4]
    assert got == {q: by_hand(rows, q) for q in queries}


def test_vectors_of_several_lengths(spark):
    rng = np.random.default_rng(6)
    rows = [(k, rng.normal(size=8)) for k in range(40)] + [(k, rng.normal(size=3)) for k in range(40, 60)] + [(60, rng.normal(size=20)), (61, [2.0]), (62, [3.0])]
    rows += [(100 + i, np.asarray(v) * 1.5 + 1e-4) for i, v in rows]
    queries = [0, 41, 60, 61, 100]
    assert nearest(spark, rows, queries) == {q: by_hand(rows, q) for q in queries}
    table = spark.createDataFrame([(i, [float(c) for c in v], 1) for i, v in rows], "vec_id long, embedding array<float>, label int")
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in grid_join.near_duplicates(table, 0.9999).collect()}
    assert {i: c for i, (_, c) in got.items()} == {i: 61 if i in (61, 62, 161, 162) else i % 100 for i, _ in rows}
    assert {i: n for i, (n, _) in got.items()} == {i: 3 if i in (61, 62, 161, 162) else 1 for i, _ in rows}


def test_page_without_head_end_and_body():
    main = "<article><h1>A &amp; B</h1><p>one\n two<p>three <b>four</article><footer>&copy; me</footer>"
    whole = html_extract.blocks("<html><head><title>t</title></head>" + main)
    for start in ("<html><head><title>t</title>", "<head><meta charset=utf-8><script>x</script><noscript><p>no</p></noscript>", "<html><head>\n"):
        assert [b.text for b in html_extract.blocks(start + main)] == [b.text for b in whole]
    assert html_extract.main_texts(["<html><head><title>t</title>" + main]) == ["A & B\none two\nthree four"]
    assert [b.text for b in html_extract.blocks("<head><title>t</title> plain words<p>more")] == ["plain words", "more"]


def test_digit_share_is_of_the_whole_block():
    from cloudlattice.llm.html_blocks import Block
    from cloudlattice.llm.html_model import inputs

    assert inputs(Block(("p",), "x" * 200 + "1" * 200, 0))[3][-1] == 0.5


def test_added_tokens_keep_their_ids(spark):
    from tokenizers import Tokenizer

    path, end = packing.default_tokenizer(), "<|endoftext|>"
    own = Tokenizer.from_file(path)
    texts = [f"some words{end}and more", end, f"{end} {end}\n  x", "none of it", "<|endoftext |>"]
    got = {r["doc_id"]: r for r in packing.pack_documents(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), path).collect()}
    for k, t in enumerate(texts):
        ids = own.encode(t, add_special_tokens=False).ids + [packing.END_ID]
        assert (got[k]["doc_tokens"], got[k]["ids_crc32"]) == (len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
    assert 50256 in own.encode(texts[0], add_special_tokens=False).ids
