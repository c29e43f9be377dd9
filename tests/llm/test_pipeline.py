import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

import corpus_pipeline
from tricount.llm import mixing, quality
from tricount.llm.queries import tokenizer_path

WORDS = "[^\\x20\\x09-\\x0D]+"


def lowered(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")


def rows():
    """Good and bad texts, exact copies in other cases, near copies, nulls, empty texts, a repeated id."""
    rng = random.Random(21)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(5))
    out = []
    for k in range(160):
        bad = k % 4 == 0
        out.append((k, " ".join(word() + ("%%%" if bad else "") for _ in range(rng.randint(30, 90))), "en", f"s{k % 3}", 1))
    for k in range(160, 200):
        t = out[k - 159][1]
        w = t.split()
        w[rng.randrange(len(w))] = word()
        out.append((k, t.upper() if k % 2 else " ".join(w), "en", f"s{k % 3}" if k % 5 else None, None))
    return [*out, (300, None, None, "s1", None), (301, "", "en", None, 0), (None, out[1][1], None, None, None), out[2], (302, "one two", "en", "s0", 2)]


@pytest.fixture(scope="module")
def corpus(spark, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("corpus"))
    spark.createDataFrame(rows(), "doc_id long, text string, lang string, source string, n_chars long").repartition(3).write.parquet(f"{folder}/documents.parquet")
    marks = [(r[0], int("%%%" not in r[1]), 0) for r in rows() if r[0] is not None and r[0] < 160]
    spark.createDataFrame(marks, "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    return folder


def told(df):
    return sorted(map(tuple, df.select("doc_id", "text", "source").collect()), key=str)


def test_every_stage_against_brute_force(spark, corpus):
    docs, kept = spark.read.parquet(f"{corpus}/documents.parquet"), {}
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        path = f"{corpus}/stage_{name}"
        stage(spark, docs, corpus).write.parquet(path)
        before, docs = docs, spark.read.parquet(path)
        assert docs.columns == columns
        kept[name] = (told(before), told(docs))

    first, good = kept["quality"]
    model = quality.train(spark.read.parquet(f"{corpus}/documents.parquet"), spark.read.parquet(f"{corpus}/labels.parquet"))
    scores = {r.doc_id: r.predicted for r in quality.score_quality(spark.read.parquet(f"{corpus}/documents.parquet"), model).collect()}
    assert good == [r for r in first if r[0] is None or scores[r[0]] == 1]
    clean = [r for r in first if r[0] is not None and r[0] < 160 and "%%%" not in r[1]]
    assert all(r in good for r in clean) and len([r for r in good if "%%%" in (r[1] or "")]) < 5

    before, after = kept["exact_dedup"]
    best = {}
    for k, t, _ in before:
        if k is not None:
            best[lowered(t)] = max(best.get(lowered(t), k), k)
    assert after == [r for r in before if r[0] is None or best[lowered(r[1])] == r[0]]

    before, after = kept["ngram_jaccard"]
    sets = {}
    for k, t, _ in before:
        w = re.findall(WORDS, lowered(t))
        sets[k] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} - {()}
    least = {k: k for k in sets if k is not None}
    for _ in range(4):
        for a in least:
            for b in least:
                shared = len(sets[a] & sets[b])
                if shared and 100 * shared >= 80 * (len(sets[a]) + len(sets[b]) - shared):
                    least[a] = least[b] = min(least[a], least[b])
    assert after == [r for r in before if r[0] is None or least[r[0]] == r[0]] and len(after) < len(before)

    before, after = kept["mix_sources"]
    copies = {}
    for r in mixing.mix(spark.read.parquet(f"{corpus}/stage_ngram_jaccard")).collect():
        copies[r.doc_id] = copies.get(r.doc_id, 0) + r.copies
    assert after == sorted([r for r in set(before) for _ in range(copies[r[0]])], key=str)  # rows of a repeated id are equal here, and copies is their sum


def test_the_whole_run_packs_what_the_mix_took(spark, corpus):
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["quality", "exact_dedup", "ngram_jaccard", "mix_sources", "packing"]
    got = corpus_pipeline.run(spark, corpus).collect()
    tok = Tokenizer.from_file(tokenizer_path())
    texts = {r[0]: r[1] for r in rows()}
    size = {k: len(tok.encode(t or "", add_special_tokens=False).ids) + 1 for k, t in texts.items()}
    pieces = {}
    for r in got:
        assert r.doc_tokens == size[r.doc_id]
        pieces.setdefault(r.doc_id, []).append((r.start, r.length, r.ids_crc32))
    for k, parts in pieces.items():
        ids = np.array([*tok.encode(texts[k] or "", add_special_tokens=False).ids, 2], dtype="<u4")
        assert sum(n for _, n, _ in parts) % size[k] == 0
        assert all(zlib.crc32(ids[a : a + n].tobytes()) == c for a, n, c in parts)
    again = corpus_pipeline.run(spark, corpus).groupBy("doc_id").agg(F.sum("length").alias("n")).collect()
    assert {r.doc_id: r.n for r in again} == {k: sum(n for _, n, _ in parts) for k, parts in pieces.items()}
