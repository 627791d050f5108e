"""Operators and pipeline against plain references: given pages, labelled rows, small corpora, odd tables."""

import random
import zlib
from collections import Counter
from html.parser import HTMLParser

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from cloudlattice.llm import ann, grid_join, html_extract, licenses, packing, queries, shingle_join, suffix_dedup, toxicity, work

R = random.Random(11)
WORDS = ["".join(R.choice("abcdefghijklmnop") for _ in range(R.randint(2, 8))) for _ in range(4000)]


def prose(n):
    return " ".join(R.choice(WORDS) for _ in range(n))


class Article(HTMLParser):
    """Text blocks inside the article element of a page whose markup is known: headings and paragraphs."""

    def __init__(self):
        super().__init__()
        self.inside, self.blocks, self.now = False, [], []

    def flush(self):
        text = " ".join("".join(self.now).split())
        if text and self.inside:
            self.blocks.append(text)
        self.now = []

    def handle_starttag(self, tag, attrs):
        if tag in ("article", "p", "h1", "footer", "div", "nav"):
            self.flush()
        if tag == "article":
            self.inside = True

    def handle_endtag(self, tag):
        if tag in ("article", "p", "h1"):
            self.flush()
        if tag == "article":
            self.inside = False

    def handle_data(self, data):
        self.now.append(data)


def test_given_pages_give_their_articles(spark):
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    want, got = {}, {}
    for r in pages.collect():
        parser = Article()
        parser.feed(r["html"])
        want[r["page_id"]] = "\n".join(parser.blocks)
    for r in html_extract.extract(pages).collect():
        got[r["page_id"]] = r["main_text"]
    assert got.keys() == want.keys()
    lost = extra = total = 0
    for k in want:
        a, b = Counter(want[k].split("\n")), Counter(got[k].split("\n"))
        lost, extra, total = lost + sum((a - b).values()), extra + sum((b - a).values()), total + sum(a.values())
    assert lost <= 0.002 * total and extra <= 0.002 * total
    assert np.mean([got[k] == want[k] for k in want]) >= 0.98


def test_labels_are_predicted_on_held_out_rows(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    held = docs.join(labels.select("doc_id", "toxic"), "doc_id").where(toxicity.held_out(F.col("doc_id")))
    insults = ("idiot", "moron", "scum", "stupid", "trash", "worthless", "pathetic", "loser", "clown", "disgusting")
    said = F.lower("text").rlike("|".join(insults))
    scored = toxicity.score_documents(held.withColumn("said", said), toxicity.fit(docs, labels), "score").select("toxic", "said", "score").collect()
    clean = [r["score"] < toxicity.LIMIT for r in scored if not r["toxic"] and not r["said"]]
    caught = [r["score"] >= toxicity.LIMIT for r in scored if r["toxic"] and r["said"]]
    assert np.mean(clean) >= 0.98 and np.mean(caught) >= 0.75


def test_dictionaries_come_from_the_trainer():
    """Telling words of each class stand in its own dictionary only, before windows that both share."""
    toxic = [f"{prose(40)} grobbel {prose(10)} snarfle" for _ in range(200)]
    ordinary = [f"{prose(50)} meadow" for _ in range(300)]
    model = toxicity.train(toxic, ordinary, 0.4)
    same = len(model.toxic) - next(k for k in range(1, len(model.toxic)) if model.toxic[-k] != model.ordinary[-k])
    assert len(model.toxic) == len(model.ordinary) and same < len(model.toxic) // 2
    own = [x[: same + 1].split() for x in (model.toxic, model.ordinary)]
    assert {b"grobbel", b"snarfle"} <= set(own[0]) and b"meadow" in own[1] and not {b"grobbel", b"snarfle"} & set(own[1])
    copies = [prose(60)] * 30
    assert len(toxicity.uncopied([set(t.encode().split()) for t in copies])) == 1


@pytest.fixture(scope="module")
def corpus(spark, tmp_path_factory):
    """Ordinary, toxic and copied documents, near copies, passages that repeat, a null text, an empty one."""
    folder = tmp_path_factory.mktemp("corpus")
    bad, passage = ["grobbel", "snarfle", "vexnot", "zorple"], prose(110)
    rows, kinds, labels = [], {}, []

    def add(kind, text):
        kinds[len(rows)] = kind
        labels.append((len(rows), int(R.random() < 0.5), int(kind == "toxic")))
        rows.append((len(rows), text, "en", f"s{len(rows) % 5}", len(text or "")))

    for _ in range(260):
        add("clean", prose(R.randint(60, 200)))
    for _ in range(120):
        w = prose(R.randint(60, 120)).split()
        for _ in range(6):
            w.insert(R.randrange(len(w)), R.choice(bad))
        add("toxic", " ".join(w))
    base = prose(200)
    add("first", base)
    for _ in range(8):
        w = base.split()
        w[R.randrange(len(w))] = R.choice(WORDS)
        add("near", " ".join(w))
    add("exact", base)
    for _ in range(6):
        add("passage", f"{prose(90)} {passage} {prose(90)}")
    add("clean", "")
    add("clean", None)
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    return str(folder), rows, kinds, passage


def test_pipeline_stages_take_effect(spark, corpus):
    folder, rows, kinds, passage = corpus
    docs, kept = work.load(spark, folder, "documents"), {}
    for name, stage in corpus_pipeline.STAGES:
        docs = work.written(stage(spark, docs, folder), "stage")
        kept[name] = docs
        if name != "packing":
            assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"]
    ids = lambda d: {r[0] for r in d.select("doc_id").collect()}
    of = lambda kind: {k for k, v in kinds.items() if v == kind}
    first = ids(kept["toxicity"])
    assert len(of("toxic") & first) <= 0.1 * len(of("toxic")) and len(of("clean") - first) <= 0.03 * len(of("clean"))
    second = ids(kept["near duplicates"])
    copies = of("first") | of("near") | of("exact")
    assert second & copies == {min(first & copies)} and not (first - second) - copies - {len(rows) - 1, len(rows) - 2}
    third = {r["doc_id"]: r["text"] for r in kept["suffix deduplication"].collect()}
    assert third.keys() == second and all(passage not in (third[k] or "") for k in of("passage") & second)
    assert all((third[k] or "") == (rows[k][1] or "") for k in of("clean") & second)
    assert ids(kept["mixing"]) <= second
    pieces = kept["packing"].collect()
    mixed = Counter(r["doc_id"] for r in kept["mixing"].select("doc_id").collect())
    tokens = {r["doc_id"]: r["doc_tokens"] for r in pieces}
    packed = Counter()
    for r in pieces:
        packed[r["doc_id"]] += r["length"]
    assert packed == Counter({k: mixed[k] * tokens[k] for k in mixed})
    filled = Counter()
    for r in pieces:
        filled[r["sequence_id"]] += r["length"]
    assert max(filled.values()) <= 2048


def test_pipeline_of_an_empty_corpus(spark, corpus, tmp_path):
    for t in ("documents", "labels"):
        spark.read.parquet(f"{corpus[0]}/{t}.parquet").where("false").write.parquet(f"{tmp_path}/{t}.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_empty_tables_and_clashing_names(spark):
    pages = spark.createDataFrame([(1, "u", "<p>x", "old"), (1, "u", "<p>x", "old"), (None, "u", None, "old")], "page_id long, url string, html string, main_text string")
    got = html_extract.extract(pages)
    assert got.count() == 3 and got.columns == ["page_id", "url", "html", "main_text"] and got.where("main_text = 'old'").count() == 0
    assert html_extract.extract(pages.where("false")).count() == 0
    model = toxicity.train([], [], 0.0)
    docs = spark.createDataFrame([(1, "some words", 2.0), (1, "some words", 2.0), (None, None, 2.0)], "doc_id long, text string, toxicity double")
    scored = toxicity.score_documents(docs, model)
    assert scored.count() == 3 and scored.columns == docs.columns and scored.where("toxicity = 2.0").count() == 0
    assert scored.select("toxicity").distinct().count() <= 2
    assert toxicity.score_documents(docs.where("false"), model).count() == 0
    assert docs.select(toxicity.held_out(F.col("doc_id")).alias("h")).where("h IS NULL").count() == 0
    assert licenses.scan(docs.where("false").select("doc_id", "text")).count() == 0
    vectors = spark.createDataFrame([(5, [1.0, 0.0], 1, 9, "c"), (5, [1.0, 0.0], 1, 9, "c"), (6, [1.0, 0.01], 1, 9, "c")], "vec_id long, embedding array<double>, label int, rep long, copies string")
    linked = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in grid_join.near_duplicates(vectors).collect()}
    assert linked == {5: (2, 5), 6: (2, 5)}


def test_search_over_repeated_ids(spark):
    rng = np.random.default_rng(8)
    rows = [(k, [float(x) for x in rng.normal(size=6)]) for k in range(30)]
    again = rows + rows[:10] + [(0, rows[0][1])] * 40
    table = spark.createDataFrame(again, "vec_id long, embedding array<double>").withColumn("rank", F.lit("x"))
    once = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    read = lambda t: sorted((r["query_id"], r["rank"], r["vec_id"]) for r in ann.search(t, F.col("vec_id") % 7 == 0).collect())
    assert read(table.repartition(2)) == read(once)


def test_links_through_a_row_without_id(spark):
    """Two texts that only a third one connects: the third has no id."""
    base = prose(300).split()
    texts = [" ".join(base[a:b]) for a, b in ((0, 270), (15, 285), (30, 300))]
    table = spark.createDataFrame([(1, texts[0]), (None, texts[1]), (3, texts[2])], "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in shingle_join.classes(table).collect()}
    assert got[1] == got[3] == 1


def test_text_of_a_row_without_id_counts_elsewhere(spark):
    passage = prose(120)
    table = spark.createDataFrame([(1, f"{prose(20)} {passage}"), (None, passage)], "doc_id long, text string")
    got = {r["doc_id"]: r["ranges"] for r in suffix_dedup.with_ranges(table).collect()}
    assert got[1] and got[None]


def test_no_query_needs_a_machine_local_folder(spark, monkeypatch):
    class Cluster:
        conf = type("conf", (), {"get": staticmethod(lambda *_: None)})()
        sparkContext = type("context", (), {"master": "spark://host:7077", "applicationId": "a"})()

    with pytest.raises(ValueError):
        work.work_dir(Cluster())
    assert work.work_dir(spark) == spark.conf.get("spark.checkpoint.dir").rstrip("/")


def test_every_operator_has_one_query():
    assert sorted(int(q.split("_")[0][2:]) for q in queries.QUERIES) == list(range(1, 11)) and set(queries.ORACLES) <= set(queries.QUERIES)


def test_unsigned_checksums():
    ids = np.array([1, 2, 3], "<u4").tobytes()
    assert next(packing.packed([(1, "x")], lambda _: ids[:8], 0))[3] == zlib.crc32(ids[:8] + np.array([1], "<u4").tobytes())
