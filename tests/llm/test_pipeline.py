"""The pipeline as a whole on empty, null, repeated and clashing rows, and its stages against brute force."""

import os
import re

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from tests.conftest import SF
from trainscape.llm import language_id, mixing, secret_scan
from trainscape.llm._common import shared_dir

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
TEXT = "the quick brown fox jumps over the lazy dog near the river bank while many small birds sing in the old trees today"
ROWS = [
    (1, TEXT, "en", "a", 1), (1, TEXT, "en", "a", 1), (2, TEXT, "en", "b", 1), (3, None, None, None, None), (4, "", "en", "a", 0), (5, "123 !!", None, "a", 1), (None, TEXT + " and more", None, None, None),
    (6, "el rio grande pasa cerca de la ciudad vieja y los barcos van despacio hacia el mar", "es", None, 1), (7, "password = hunter2hunter2 was written in the old book of the town", "en", "c", 1), (8, " ".join(f"word{i % 301}q{i}" for i in range(20_000)), "en", "c", 1),
]


def made(spark, tmp_path, rows, more=()):
    df = spark.createDataFrame(rows, SCHEMA).withColumns({c: F.lit("x") for c in more})
    df.write.parquet(f"{tmp_path}/documents.parquet")
    return str(tmp_path)


def test_run_on_an_empty_table(spark, tmp_path):
    got = corpus_pipeline.run(spark, made(spark, tmp_path, []))
    assert got.collect() == [] and {"doc_id", "n_tokens", "ids", "round_trip"} <= set(got.columns)


@pytest.mark.parametrize("more", [(), ("row", "component_id", "kept", "score", "lang_pred", "salt", "digest", "ids", "taken")])
def test_run_on_odd_rows(spark, tmp_path, more):
    rows = corpus_pipeline.run(spark, made(spark, tmp_path, ROWS, more)).collect()
    ids = [r["doc_id"] for r in rows]
    assert not {2, 3, 4, 5} & set(ids) and set(ids) <= {None, 1, 6, 7, 8} and all(r["round_trip"] for r in rows)


def test_run_on_rows_of_nulls(spark, tmp_path):
    assert corpus_pipeline.run(spark, made(spark, tmp_path, [(None,) * 5] * 3)).collect() == []


def test_run_leaves_one_step(spark):
    steps = f"{shared_dir(spark).removeprefix('file:')}/steps"
    before = set(os.listdir(steps)) if os.path.isdir(steps) else set()
    got = corpus_pipeline.run(spark, SF)
    left = set(os.listdir(steps)) - before
    assert os.path.basename(got.step_path) in left and len(left) <= 8


def test_language_stage_keeps_all_texts_with_letters(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = {r["doc_id"] for r in corpus_pipeline.identified(spark, docs, SF).collect()}
    assert kept == {r["doc_id"] for r in docs.collect() if r["text"] and any(c.isalpha() for c in r["text"])}


def test_languages_equal_brute_force(spark):
    """Bundles by one product of rotated letter vectors at a time, cosines by plain sums."""
    import numpy as np

    prototypes = language_id.learn_prototypes(language_id.train_rows(spark.read.parquet(f"{SF}/documents.parquet")))
    texts = ["the cat and the dog", "El río", "a", "x y z", "Über die Brücke", "12 ab"]
    got = {r["doc_id"]: r for r in language_id.identify_language(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), prototypes).collect()}
    for i, text in enumerate(texts):
        letters = re.sub(r"[\W\d_]+", " ", f" {text.lower()} ")
        letters = letters + " " * max(0, 3 - len(letters))
        total = np.zeros(language_id.DIMS)
        for k in range(len(letters) - 2):
            gram = np.ones(language_id.DIMS)
            for place in range(3):
                gram *= np.roll(language_id.letter_vectors(np.array([ord(letters[k + place])]), language_id.DIMS)[0], place)
            total += gram
        cosines = {lang: float(total @ v) / np.linalg.norm(total) for lang, v in prototypes.items()}
        best = max(cosines, key=cosines.get)
        assert got[i]["lang_pred"] == best and abs(got[i]["score"] - max(0, cosines[best])) < 1e-4


def test_secret_stage_equals_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    got = {r["doc_id"]: (r["text"], r["n_chars"]) for r in corpus_pipeline.without_secrets(spark, docs, SF).collect()}
    for r in docs.collect():
        text = list(r["text"] or "")
        covered = [None] * len(text)
        for s, k, e in secret_scan.find_secrets(r["text"]):
            for at in range(s, e):
                covered[at] = covered[at] or (s, secret_scan.KINDS[k])
        # of overlapping spans the first stands for all
        out, at = [], 0
        while at < len(text):
            if covered[at] is None:
                out.append(text[at])
                at += 1
            else:
                out.append(f"<{covered[at][1]}>")
                stop = max(e for s, _, e in secret_scan.find_secrets(r["text"]) if s <= at < e)
                while True:
                    further = max([e for s, _, e in secret_scan.find_secrets(r["text"]) if s < stop <= e or at <= s < stop], default=stop)
                    if further <= stop:
                        break
                    stop = further
                at = stop
        assert got[r["doc_id"]] == (("".join(out), len("".join(out))) if r["text"] is not None else (None, None))


def test_mixing_stage_equals_the_query(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    times = {}
    for r in corpus_pipeline.mixed(spark, docs, SF).collect():
        times[r["doc_id"]] = times.get(r["doc_id"], 0) + 1
    for r in mixing.mix_sources(docs).collect():
        assert r["taken"] == r["size"] * times.get(r["doc_id"], 0)
