"""Language identification by hyperdimensional profiles."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trainscape.llm._common import checkpointed, crc_mod, forget, mix64, small_side, table, text_chunks

#: Dimensions of the random letter vectors and letters per n-gram.
DIMS, ORDER = 1024, 3
#: Each language learns from at most this many documents (one for each salt of the doc_id hash).
DOCS_PER_LANGUAGE = 512
UND = "und"
_GAP = ord(" ")
#: Parts of one that the unit vectors of documents are rounded to, so that their sums are whole numbers and no order changes them.
_PARTS = 2**32


def letter_codes(text: str | None) -> np.ndarray:
    """Code points of the lower-cased text, each run of anything but letters as one space; empty if there is no letter."""
    if not text:
        return np.empty(0, np.int64)
    codes = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
    low = codes < 128
    letter = np.where(low, (codes >= 97) & (codes <= 122), False)
    if not low.all():
        other = np.unique(codes[~low])
        alpha = other[np.fromiter((chr(c).isalpha() for c in other), bool, len(other))]
        letter |= np.isin(codes, alpha)
    if not letter.any():
        return np.empty(0, np.int64)
    codes = np.where(letter, codes, _GAP)
    keep = letter | np.concatenate([[True], letter[:-1]])
    return np.concatenate([[_GAP], codes[keep], [_GAP]]) if letter[0] else np.concatenate([codes[keep], [_GAP]])


def letter_vectors(letters: np.ndarray, dims: int) -> np.ndarray:
    """A random vector of -1 and 1 for each code point, the same in every process."""
    words = (dims + 63) // 64
    seeds = letters.astype(np.uint64)[:, None] * np.uint64(words) + np.arange(words, dtype=np.uint64)
    bits = np.unpackbits(mix64(mix64(seeds + np.uint64(0x9E3779B97F4A7C15))).view(np.uint8).reshape(len(letters), -1), axis=1)[:, :dims]
    return bits.astype(np.float32) * 2 - 1


def gram_vectors(grams: np.ndarray, order: int, dims: int) -> np.ndarray:
    """The vector of each n-gram: the product of its letters' vectors, each rotated by its place."""
    out = np.ones((len(grams), dims), np.float32)
    for place in range(order):
        letters, inverse = np.unique((grams >> (21 * place)) & 0x1FFFFF, return_inverse=True)
        out *= np.roll(letter_vectors(letters, dims), place, axis=1)[inverse]
    return out


def bundles(texts: list[str | None], order: int, dims: int) -> np.ndarray:
    """One vector per text: the sum of its n-gram vectors; zeros for a text without letters."""
    grams, owners = [], []
    for i, text in enumerate(texts):
        codes = letter_codes(text)
        if len(codes):
            codes = np.concatenate([codes, np.full(max(0, order - len(codes)), _GAP)])
            packed = np.zeros(len(codes) - order + 1, np.int64)
            for place in range(order):
                packed |= codes[place : place + len(packed)] << (21 * place)
            grams.append(packed)
            owners.append(np.full(len(packed), i))
    out = np.zeros((len(texts), dims), np.float32)
    if not grams:
        return out
    distinct, inverse = np.unique(np.concatenate(grams), return_inverse=True)
    cells, counts = np.unique(np.concatenate(owners) * len(distinct) + inverse, return_counts=True)
    step = 2048
    for start in range(0, len(distinct), step):
        part = cells[(low := cells % len(distinct)) // step == start // step]
        table_ = np.zeros((len(texts), min(step, len(distinct) - start)), np.float32)
        table_[part // len(distinct), part % len(distinct) - start] = counts[low // step == start // step]
        out += table_ @ gram_vectors(distinct[start : start + step], order, dims)
    return out


def _profile(order: int, dims: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, np.ndarray] = {}
        for whole in batches:
            for batch in text_chunks(whole):
                for lang, vector in zip(batch.column("lang").to_pylist(), bundles(batch.column("text").to_pylist(), order, dims)):
                    norm = float(np.linalg.norm(vector))
                    if norm:
                        sums[lang] = sums.get(lang, 0) + np.rint(vector.astype(float) / norm * _PARTS).astype(np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.string()), pa.array(list(sums.values()), pa.list_(pa.int64()))], ["lang", "v"])

    return run


def learn_prototypes(labelled: DataFrame, per_language: int = DOCS_PER_LANGUAGE, order: int = ORDER, dims: int = DIMS) -> dict[str, np.ndarray]:
    """A unit vector per language, from (doc_id, text, lang) rows with a language.

    Each language learns from the documents of smallest hash in each of
    `per_language` salts, so a frequent language costs no more than a rare one.
    """
    h = F.xxhash64("doc_id")
    picked = labelled.select("lang", F.pmod(h, F.lit(per_language)).alias("salt"), h.alias("h")).groupBy("lang", "salt").agg(F.min("h").alias("h")).select("lang", "h")
    picked = checkpointed(picked)
    chosen = labelled.withColumn("h", h).join(small_side(picked), ["lang", "h"], "left_semi").select("lang", "text")
    sums = chosen.mapInArrow(_profile(order, dims), "lang string, v array<long>").select("lang", F.posexplode("v").alias("i", "x")).groupBy("lang", "i").agg(F.sum("x").alias("x"))
    found: dict[str, np.ndarray] = {}
    for row in sums.groupBy("lang").agg(F.array_sort(F.collect_list(F.struct("i", "x"))).alias("v")).select("lang", F.col("v.x").alias("v")).collect():
        vector = np.asarray(row["v"], float)
        found[row["lang"]] = (vector / np.linalg.norm(vector)).astype(np.float32)
    forget(picked)
    return dict(sorted(found.items()))


def _classify(prototypes: dict[str, np.ndarray], order: int, dims: int):
    names, matrix = [*prototypes], np.array([*prototypes.values()], np.float32).reshape(-1, dims).T

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in text_chunks(whole, limit=400_000):
                vectors = bundles(batch.column("text").to_pylist(), order, dims)
                norms = np.linalg.norm(vectors, axis=1)
                if names:
                    cosines = vectors @ matrix / np.where(norms, norms, 1)[:, None]
                    best = cosines.argmax(axis=1)
                    found = [names[b] if n else UND for b, n in zip(best, norms)]
                    score = np.where(norms > 0, np.clip(cosines.max(axis=1), 0, 1), 0).astype(float)
                else:
                    found, score = [UND] * batch.num_rows, np.zeros(batch.num_rows)
                yield pa.RecordBatch.from_arrays([*(batch.column(i) for i, f in enumerate(batch.schema) if f.name != "text"), pa.array(found, pa.string()), pa.array(score)], [*(f.name for f in batch.schema if f.name != "text"), "lang_pred", "score"])

    return run


def identify_language(docs: DataFrame, prototypes: dict[str, np.ndarray], order: int = ORDER, dims: int = DIMS) -> DataFrame:
    """(doc_id, lang_pred, score): the language whose prototype has the greatest cosine with the text's bundle.

    Every letter has a random vector of -1 and 1; an n-gram is the product of
    its letters' vectors rotated by their places, a text the sum of its
    n-grams. Texts that are null or hold no letter are `und` with score 0, as
    is everything when no prototype was learnt. Of equal cosines the language
    first in the alphabet wins. Rows are judged alone and in whole; negative
    cosines score 0. Other columns are ignored.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(_classify(prototypes, order, dims), "doc_id long, lang_pred string, score double")


def with_language(docs: DataFrame, prototypes: dict[str, np.ndarray], least: float = 0.0, order: int = ORDER, dims: int = DIMS) -> DataFrame:
    """The documents that have a language, with lang set to it, other columns as they are.

    Texts without letters and texts whose cosine with each prototype is under `least` go.
    """
    names = docs.columns
    found = docs.select(F.struct(*names).alias("row"), F.col("text").cast("string").alias("text"))
    found = found.mapInArrow(_classify(prototypes, order, dims), f"row {found.schema['row'].dataType.simpleString()}, lang_pred string, score double")
    found = found.where((F.col("lang_pred") != UND) & (F.col("score") >= least))
    return found.select(*(F.col("lang_pred").alias(n) if n == "lang" else F.col(f"row.`{n}`").alias(n) for n in names))


def train_rows(docs: DataFrame) -> DataFrame:
    """Documents to learn from: crc32 of the id mod 4 is not 2, the language is not null."""
    return docs.where((crc_mod(F.col("doc_id"), 4) != 2) & F.col("lang").isNotNull()).select("doc_id", F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"))


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = identify_language(docs, learn_prototypes(train_rows(docs)))
    return found.select("doc_id", F.coalesce(crc_mod(F.col("doc_id"), 4) == 2, F.lit(False)).alias("held_out"), "lang_pred", "score")
