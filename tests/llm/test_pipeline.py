"""The stages on the smallest tables: each against brute force on its own input, and what is
left when the training-data operators are taken out."""

import hashlib
import itertools
import pathlib
import re
import shutil
import subprocess
import sys

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from conftest import ROOT
from matchloom.llm import mixing
from matchloom.llm.queries import QUERIES, vocabulary

SMALL = "/root/testdata/sf0.001"
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.fixture(scope="module")
def stages(spark, tmp_path_factory):
    docs, out = spark.read.parquet(f"{SMALL}/documents.parquet"), {}
    for name, stage in corpus_pipeline.STAGES:
        path = str(tmp_path_factory.mktemp("stage") / name)
        stage(spark, docs, SMALL).write.parquet(path)
        out[name] = (docs, spark.read.parquet(path))
        docs = out[name][1]
    return out


def test_all_but_the_last_keep_the_columns(stages):
    for name, (_, after) in list(stages.items())[:-1]:
        assert after.columns == COLUMNS, name


def test_toxic_documents_go_and_clean_ones_stay(spark, stages):
    before, after = stages["toxicity"]
    kept = {r["doc_id"] for r in after.select("doc_id").collect()}
    labels = {r["doc_id"]: r["toxic"] for r in spark.read.parquet(f"{SMALL}/labels.parquet").where("toxic is not null").collect()}
    clean, toxic = ([i for i, t in labels.items() if t == k] for k in (0, 1))
    assert sum(i in kept for i in clean) >= 0.97 * len(clean) and sum(i in kept for i in toxic) <= 0.2 * len(toxic)
    assert after.join(before, COLUMNS, "left_anti").isEmpty()


def test_texts_in_a_language_stay(stages):
    before, after = stages["language_id"]
    gone = before.join(after, "doc_id", "left_anti").select("text").collect()
    assert len(gone) <= 0.03 * before.count() + sum(not any(map(str.isalpha, r["text"] or "")) for r in gone)


def test_one_document_of_each_group_stays(stages):
    before, after = stages["simhash_near_dedup"]
    sets = {}
    for r in before.select("doc_id", "text").collect():
        w = (r["text"] or "").encode().lower().split()
        sets[r["doc_id"]] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))}
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in itertools.combinations(sorted(sets), 2):
        if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
            x, y = sorted((find(a), find(b)))
            root[y] = x
    assert {r["doc_id"] for r in after.select("doc_id").collect()} == {i for i in sets if find(i) == i}


def test_mix_takes_words_near_the_targets(stages):
    before, after = stages["mixing"]
    targets = {r["source"]: r["target"] for r in mixing.source_targets(mixing.sized_documents(before)).collect()}
    size = F.sum(F.regexp_count("text", F.lit(mixing.WORD)))
    taken = {r["source"]: r["n"] for r in after.groupBy("source").agg(size.alias("n")).collect()}
    for s, t in targets.items():
        assert abs(taken.get(s, 0) - t) <= 0.06 * t + 64, s
    own = {r["doc_id"]: set(re.findall(r"[^\x20\x09-\x0d]+", r["text"])) for r in before.collect()}
    assert all(set(re.findall(r"[^\x20\x09-\x0d]+", r["text"])) <= own[r["doc_id"]] for r in after.collect())
    assert after.where(F.length("text") != F.col("n_chars")).isEmpty()


def test_ids_are_those_of_the_library(stages):
    from tokenizers import Tokenizer

    before, after = stages["bpe"]
    library = Tokenizer.from_file(vocabulary("byte_bpe_50k.json"))
    want = []
    for r in before.collect():
        ids = library.encode(r["text"] or "", add_special_tokens=False).ids
        want.append((r["doc_id"], len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((r["text"] or "").encode()).hexdigest()))
    assert sorted(map(tuple, after.collect())) == sorted(want)


def test_stages_take_odd_tables(spark, tmp_path):
    rows = [(1, None, None, None, None), (None, "some words here", "en", "a", 15), (2, "", "en", "a", 0), (3, "the cat sat on the mat " * 9, "en", "b", 0), (3, "the cat sat on the mat " * 9, "en", "b", 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").withColumn("score", F.lit("x"))
    spark.createDataFrame([(3, None, 0), (None, 1, 1)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    for table in (docs, docs.where("false")):
        for name, stage in corpus_pipeline.STAGES:
            out = stage(spark, table, str(tmp_path))
            assert out.count() <= 3 * table.count(), name
            assert name == "bpe" or out.columns == docs.columns, name


def test_every_operator_is_registered():
    assert [n.split("_")[0] for n in QUERIES] == [f"op{k}" for k in range(1, 11)]


def test_the_rest_works_without_the_operators(tmp_path):
    copy = tmp_path / "repo"
    shutil.copytree(ROOT, copy, ignore=shutil.ignore_patterns(".git", "llm", "corpus_pipeline.py", "__pycache__"))
    code = "import __spark_entry__ as e; assert len(e.queries()) > 90 and not any(k.startswith('op') or k == 'pipeline' for k in e.queries()) and set(e.oracle_sql()) <= set(e.queries())"
    subprocess.run([sys.executable, "-c", code], cwd=copy, check=True, env={"PATH": "/usr/bin:/bin"})


def test_tables_of_the_near_duplicate_stage_go_with_it(spark, monkeypatch):
    made = []

    class Seen(corpus_pipeline.Scratch):
        def __init__(self, *args):
            super().__init__(*args)
            made.append(self)

    monkeypatch.setattr(corpus_pipeline, "Scratch", Seen)
    line = "one two three four five six seven eight nine ten eleven twelve"
    rows = [(1, line), (2, line), (2, line + " more"), (3, "some other text that is like none of these"), (None, line)]
    kept = corpus_pipeline.drop_near_duplicates(spark, spark.createDataFrame(rows, "doc_id long, text string"), "")
    left = [p.name.split("-")[1] for s in made for p in pathlib.Path(s.root.removeprefix("file://")).iterdir()]
    assert sorted(left) == ["gone", "once"]
    assert sorted(kept.collect(), key=str) == [(1, line), (3, rows[3][1]), (None, line)]
