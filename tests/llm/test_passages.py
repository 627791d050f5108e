"""Passages of over 50 words that repeat, whatever their bytes: the pipeline's stage against a plain reference."""

import random
import re
from collections import Counter

import numpy as np

import corpus_pipeline
from cloudlattice.llm import suffix_dedup

R = random.Random(23)
WORDS = ["".join(R.choice("abcdefgé") for _ in range(R.randint(1, 5))) for _ in range(3000)]


def prose(n):
    return [R.choice(WORDS) for _ in range(n)]


def without(texts, words, length):
    """Texts without the bytes of ``length``-byte strings and ``words``-word passages that start anywhere else too."""
    split = [[m.span() for m in re.finditer(rb"[^\x20\x09-\x0D]+", t)] for t in texts]
    told = [[t[a:b] for a, b in s] for t, s in zip(texts, split)]
    passages = Counter(tuple(w[k : k + words]) for w in told for k in range(len(w) - words + 1))
    strings = Counter(t[k : k + length] for t in texts for k in range(len(t) - length + 1))
    out = []
    for t, s, w in zip(texts, split, told):
        gone = np.zeros(len(t), bool)
        for k in range(len(t) - length + 1):
            if strings[t[k : k + length]] > 1:
                gone[k : k + length] = True
        for k in range(len(w) - words + 1):
            if passages[tuple(w[k : k + words])] > 1:
                gone[s[k][0] : s[k + words][0] if k + words < len(s) else len(t)] = True
        out.append(bytes(np.frombuffer(t, np.uint8)[~gone]).decode("utf-8", "ignore"))
    return out


def test_short_passages_of_many_words_go_whole(spark):
    many, few, over, long = prose(60), prose(50), prose(51), ["".join(prose(8)) for _ in range(30)]
    assert len(" ".join(many).encode()) < 400 < len(" ".join(long).encode())
    texts = [" ".join(prose(R.randint(0, 90)) + x + prose(R.randint(0, 90))) for x in (many, few, over, long) for _ in range(3)]
    texts += ["\n".join(prose(5) + many), " \t ".join(over), " ".join(many).upper(), " ".join(many[:30] + prose(1) + many[31:]), "a " * 70, "", " ", "é" * 900]
    texts += [" ".join(prose(40) + many[:52] + prose(3) + many[9:] + over)]
    rows = [*enumerate(texts), (len(texts), None)]
    docs = spark.createDataFrame([(k, t, "en", "web", len(t or "")) for k, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    got = {r["doc_id"]: r for r in corpus_pipeline.unrepeated(spark, docs, "").collect()}
    want = without([t.encode() for t in texts], 51, 400)
    assert {k: got[k]["text"] for k in range(len(texts))} == dict(enumerate(want)) and got[len(texts)]["text"] is None
    assert all(r["n_chars"] == len(r["text"] or "") for r in got.values())
    assert not any(" ".join(many[:51]) in t for t in want) and sum(" ".join(few) in t for t in want) == 3
    assert suffix_dedup.deduplicated(docs.where("false"), words=51).count() == 0
