"""Toxicity by class-conditional Kneser-Ney word models with a shared backoff."""

from __future__ import annotations

import re
import uuid
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trainscape.llm._common import checkpointed, crc_mod, forget, mix64, salted_join, shared_dir, skew_join, small_side, table, text_chunks
from trainscape.llm._storage import resolve, write_whole
from trainscape.llm.near_dedup import _WordHashes, shingle_sets

DISCOUNT = 0.75
#: Of this many parts of the texts, dealt by their smallest run of so many words, one gives the calibration before it is counted too.
PARTS, COPY_WIDTH = 4, 3
#: Texts are near copies if they share this percentage of those runs.
COPY_PERCENT = 80
#: Log-likelihood ratios from which words are counted as evidence; the share of such words among ordinary texts is learnt.
BARS = (1.75, 2.25, 2.75, 3.25)
#: Bytes of text whose counts are joined before they are exchanged.
COUNT_CHARS = 8_000_000
_WORDS = re.compile(r"[^\W\d_]+")
#: Ranges of pair keys, by their first bits; and the pairs up to which a model holds them itself.
BUCKETS, PAIRS_HELD = 4096, 1_000_000
#: Documents to learn from that may be broadcast by id.
BROADCAST_LABELS = 2_000_000
#: Stands before the first word of a text.
_START = np.zeros(1, np.int64)


def toxic_words(text: str | None) -> list[str]:
    return _WORDS.findall(text.lower()) if text else []


def word_keys(text: str | None, hashes: _WordHashes) -> np.ndarray:
    """64-bit hashes of a text's words, in order."""
    words = toxic_words(text)
    return np.fromiter(map(hashes.__getitem__, words), np.uint64, len(words)).view(np.int64)


def _pair_keys(v: np.ndarray, w: np.ndarray) -> np.ndarray:
    return mix64(v.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + w.view(np.uint64)).view(np.int64)


def _looked_up(keys: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of the wanted keys among sorted ones, and which of them are there; each different key is sought once, in order."""
    if not len(keys):
        return np.zeros(len(wanted), np.int64), np.zeros(len(wanted), bool)
    sought, which = np.unique(wanted, return_inverse=True)
    at = np.minimum(np.searchsorted(keys, sought), len(keys) - 1)
    return at[which], (keys[at] == sought)[which]


def _bucket(keys: np.ndarray) -> np.ndarray:
    return (keys >> 52) + BUCKETS // 2


@dataclass
class PairFiles:
    """Sorted runs of pair keys and their values in files that all machines share: (path, first row, rows) of each range of keys.

    Local files are mapped, so that the processes of a machine share their pages; others are read.
    """

    runs: dict[int, list[tuple[str, int, int]]]
    opened: dict[str, tuple[np.ndarray, np.ndarray]] = field(default_factory=dict)

    def __getstate__(self) -> dict:
        return {"runs": self.runs, "opened": {}}

    def _open(self, path: str) -> tuple[np.ndarray, np.ndarray]:
        if path not in self.opened:
            store, where = resolve(path)
            data = np.memmap(where, np.uint8, "r") if store.type_name == "local" else np.frombuffer(store.open_input_file(where).read(), np.uint8)
            n = len(data) // 12
            self.opened[path] = data[: 8 * n].view(np.int64), data[8 * n :].view(np.float32)
        return self.opened[path]

    def values(self, wanted: np.ndarray) -> np.ndarray:
        """The value of each wanted key; 0 for one that is not there."""
        sought, which = np.unique(wanted, return_inverse=True)
        out, of = np.zeros(len(sought)), _bucket(sought)
        cuts = np.flatnonzero(np.diff(of)) + 1
        for lo, hi in zip([0, *cuts], [*cuts, len(sought)] if len(sought) else []):
            for path, first, n in self.runs.get(int(of[lo]), ()):
                keys, values = (x[first : first + n] for x in self._open(path))
                at = np.minimum(np.searchsorted(keys, sought[lo:hi]), n - 1)
                there = keys[at] == sought[lo:hi]
                out[lo:hi][there] = values[at[there]]
        return out[which]


@dataclass
class ToxicityModel:
    """Log-likelihood ratios (toxic over ordinary) of words and contexts, what word pairs add to them, and the calibration."""

    prior: float
    weights: np.ndarray
    usual: np.ndarray = field(default_factory=lambda: np.full(len(BARS), 0.01))
    word_keys: np.ndarray = field(default_factory=lambda: np.empty(0, np.int64))
    word: np.ndarray = field(default_factory=lambda: np.empty(0))
    context_keys: np.ndarray = field(default_factory=lambda: np.empty(0, np.int64))
    context: np.ndarray = field(default_factory=lambda: np.empty(0))
    pair_keys: np.ndarray = field(default_factory=lambda: np.empty(0, np.int64))
    pair: np.ndarray = field(default_factory=lambda: np.empty(0, np.float32))
    pair_files: PairFiles | None = None

    def measures(self, texts: list[str | None], hashes: _WordHashes) -> np.ndarray:
        """One row per text: the sum of log-likelihood ratios, the number of words, those over each bar."""
        found = [word_keys(t, hashes) for t in texts]
        n = np.array([len(w) for w in found])
        out = np.zeros((len(texts), MEASURES))
        out[:, 1] = n
        if not n.sum() or not len(self.word_keys):
            return out
        w, owner = np.concatenate(found), np.repeat(np.arange(len(texts)), n)
        v = np.concatenate([_START, w[:-1]])
        v[(np.cumsum(n) - n)[n > 0]] = 0
        place, known = _looked_up(self.word_keys, w)
        v, w, owner, word = v[known], w[known], owner[known], self.word[place[known]]
        ratio = word.copy()
        for keys, values, wanted in ((self.context_keys, self.context, v), (self.pair_keys, self.pair, _pair_keys(v, w))):
            place, there = _looked_up(keys, wanted)
            ratio[there] += values[place[there]]
        if self.pair_files:
            ratio += self.pair_files.values(_pair_keys(v, w))
        out[:, 0] = np.bincount(owner, ratio, len(texts))
        for i, bar in enumerate(BARS):
            out[:, 2 + i] = np.bincount(owner[word >= bar], minlength=len(texts))
        return out

    def features(self, found: np.ndarray) -> np.ndarray:
        """The mean ratio, and by how many deviations the words over each bar exceed what ordinary texts of that length have."""
        n, over = np.maximum(found[:, 1], 1), found[:, 2:]
        expected = n[:, None] * self.usual
        excess = np.clip((over - expected) / np.sqrt(expected + 1), -3, 12)
        return np.column_stack([np.ones(len(n)), 10 * np.tanh(found[:, 0] / n), excess])

    def scores(self, texts: list[str | None], hashes: _WordHashes | None = None) -> np.ndarray:
        found = self.measures(texts, _WordHashes() if hashes is None else hashes)
        z = self.features(found) @ self.weights
        return np.where(found[:, 1] > 0, 1 / (1 + np.exp(-np.clip(z, -40, 40))), self.prior)


#: Numbers of a measured text, and of the features made of them.
MEASURES, FEATURES = 2 + len(BARS), 2 + len(BARS)


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, steps: int = 40) -> np.ndarray:
    """Weights of a ridge logistic regression in which both classes weigh what they have."""
    w = np.zeros(x.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -40, 40)))
        s = np.maximum(p * (1 - p), 1e-6)
        w += np.linalg.solve((x * s[:, None]).T @ x + ridge * np.eye(len(w)) * 0.1, x.T @ (y - p) - 0.1 * ridge * w)
    return w


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Counts of word pairs by class: (v, w, n0, n1); the first word of a text follows a start mark."""
    hashes = _WordHashes()
    for whole in batches:
        for batch in text_chunks(whole, limit=COUNT_CHARS):
            texts = [word_keys(t, hashes) for t in batch.column("text").to_pylist()]
            toxic = np.repeat(np.asarray(batch.column("toxic").to_pylist(), bool), [len(t) for t in texts])
            if not len(toxic):
                continue
            w = np.concatenate(texts)
            v = np.concatenate([np.concatenate([_START, t[:-1]]) for t in texts if len(t)])
            _, first, which = np.unique(_pair_keys(v, w), return_index=True, return_inverse=True)
            n = [np.bincount(which[toxic == c], minlength=len(first)) for c in (0, 1)]
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in (v[first], w[first], *n)], ["v", "w", "n0", "n1"])


def _marked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Adds the two smallest hashes of a text's runs; texts without words are left out."""
    hashes = _WordHashes()
    for whole in batches:
        for batch in text_chunks(whole):
            sets = shingle_sets(batch.column("text").to_pylist(), COPY_WIDTH, hashes)
            own = np.flatnonzero([len(s) > 0 for s in sets])
            least = [np.array([mix64(sets[i] ^ salt).min() for i in own], np.uint64).view(np.int64) for salt in mix64(np.arange(1, 3, dtype=np.uint64))]
            part = (least[1].view(np.uint64) % np.uint64(PARTS) == PARTS - 1).astype(np.int32)
            kept = batch.take(pa.array(own))
            yield pa.RecordBatch.from_arrays([*(kept.column(c) for c in ("doc_id", "toxic", "text")), *map(pa.array, (*least, part))], ["doc_id", "toxic", "text", "least0", "least1", "part"])


def _distinct(sample: DataFrame) -> DataFrame:
    """The sample (doc_id, toxic, text) with near copies counted once in each class, and its part.

    Near copies are looked for among texts of one class whose smallest hash of a run of COPY_WIDTH words is the same, by
    two hashes in turn: a text goes if its runs are confirmed to overlap by COPY_PERCENT with those of the smallest doc_id
    there. The part comes from such a hash too, so the few that are missed mostly share a part and what the counts have
    seen doesn't come back in the calibration. Only numbers are grouped; texts move if they share a hash with another.
    """
    row = ["doc_id", "toxic", "t"]
    marked = sample.where("text is not null").select("doc_id", F.col("toxic").cast("int").alias("toxic"), "text").mapInArrow(_marked, "doc_id long, toxic int, text string, least0 long, least1 long, part int")
    rows = checkpointed(marked.withColumn("t", F.xxhash64("text")))
    if rows.groupBy(*row).count().where("count > 1").limit(1).count():
        once = checkpointed(rows.dropDuplicates(["doc_id", "toxic", "text"]))
        forget(rows)
        rows = once
    alive, total = rows, rows.count()
    for salt in (0, 1):
        numbers = alive.select(*row, F.col(f"least{salt}").alias("least"))
        groups = checkpointed(numbers.groupBy("toxic", "least").agg(F.min("doc_id").alias("head"), F.min(F.struct("doc_id", "t")).alias("first"), F.count("*").alias("n")).where("n > 1").select("toxic", "least", "head", F.col("first.t").alias("head_t"), "n"))
        near = checkpointed(skew_join(numbers, groups, ["toxic", "least"], "n", total).where("doc_id <> head").select(*row, "head", "head_t"))
        of = alive.select(*row, "text")
        heads = of.join(small_side(near.select(F.col("head").alias("doc_id"), "toxic", F.col("head_t").alias("t")).distinct()), row, "left_semi").select(F.col("doc_id").alias("head"), "toxic", F.col("t").alias("head_t"), F.col("text").alias("text_a"))
        pairs = salted_join(of.join(small_side(near), row).withColumnRenamed("text", "text_b"), heads, ["head", "toxic", "head_t"], "doc_id", near)
        gone = checkpointed(pairs.select("doc_id", "toxic", "t", "text_a", "text_b").mapInArrow(_copies, "doc_id long, toxic int, t long"))
        forget(groups, near)
        alive = alive.join(small_side(gone), row, "left_anti")
    out = alive.select("doc_id", "toxic", "part", "text")
    out.step_path = rows.step_path
    return out


def _copies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The rows whose text_b is a near copy of text_a."""
    hashes = _WordHashes()
    for whole in batches:
        for batch in text_chunks(whole, "text_b"):
            a, b = (batch.column(c).to_pylist() for c in ("text_a", "text_b"))
            first = {x: s for x, s in zip(dict.fromkeys(a), shingle_sets(list(dict.fromkeys(a)), COPY_WIDTH, hashes))}
            both = [(len(np.intersect1d(first[x], s, assume_unique=True)), len(first[x]) + len(s)) for x, s in zip(a, shingle_sets(b, COPY_WIDTH, hashes))]
            yield batch.select(["doc_id", "toxic", "t"]).filter(pa.array([100 * n >= COPY_PERCENT * (size - n) for n, size in both], pa.bool_()))


def _language_models(counted: DataFrame, model: ToxicityModel) -> bool:
    """Fits the models of both classes to counts (v, w, n0, n1) and puts their ratios into model; False if a class has no words."""
    seen = [(F.col(f"n{c}") > 0).cast("long") for c in (0, 1)]
    words = counted.groupBy("w").agg(*(F.sum(seen[c]).alias(f"c{c}") for c in (0, 1)), F.count("*").alias("both")).orderBy("w").toArrow()
    c = [words[f"c{c}"].to_numpy().astype(float) for c in (0, 1)]
    total = [x.sum() for x in c]
    if not len(words) or not all(total):
        return False
    both = words["both"].to_numpy().astype(float)
    lower = [(np.maximum(x - DISCOUNT, 0) + DISCOUNT * (x > 0).sum() * both / both.sum()) / t for x, t in zip(c, total)]
    model.word_keys, model.word = words["w"].to_numpy(), np.log(lower[1] / lower[0])

    contexts = counted.groupBy("v").agg(*(F.sum(f"n{c}").alias(f"n{c}") for c in (0, 1)), *(F.sum(seen[c]).alias(f"f{c}") for c in (0, 1))).orderBy("v").toArrow()
    n = [contexts[f"n{c}"].to_numpy().astype(float) for c in (0, 1)]
    left = [np.where(n[c] > 0, DISCOUNT * contexts[f"f{c}"].to_numpy() / np.maximum(n[c], 1), 1.0) for c in (0, 1)]
    model.context_keys, model.context = contexts["v"].to_numpy(), np.log(left[1] / left[0])

    shared = counted.sparkSession.sparkContext.broadcast((model.word_keys, lower, model.context_keys, n, left))

    def ratios(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, lower, contexts, n, left = shared.value
        for batch in batches:
            v, w = batch.column("v").to_numpy(), batch.column("w").to_numpy()
            at, of = np.searchsorted(words, w), np.searchsorted(contexts, v)
            # over what an unseen pair of the two words has: left * lower
            gain = [np.log1p(np.maximum(batch.column(f"n{c}").to_numpy() - DISCOUNT, 0) / np.maximum(n[c][of], 1) / (left[c][of] * lower[c][at])) for c in (0, 1)]
            yield pa.RecordBatch.from_arrays([pa.array(_pair_keys(v, w)), pa.array((gain[1] - gain[0]).astype(np.float32))], ["key", "ratio"])

    pairs = counted.select("v", "w", "n0", "n1").mapInArrow(ratios, "key long, ratio float")
    model.pair_files = None
    if words["both"].to_numpy().sum() <= PAIRS_HELD:
        found = pairs.toArrow()
        keys = found["key"].to_numpy()
        order = np.argsort(keys)
        model.pair_keys, model.pair = keys[order], found["ratio"].to_numpy()[order]
    else:
        model.pair_keys, model.pair, model.pair_files = np.empty(0, np.int64), np.empty(0, np.float32), _pair_files(pairs)
    shared.unpersist()
    return True


def _pair_files(pairs: DataFrame) -> PairFiles:
    """Writes (key, ratio) rows where they lie, sorted by task, into the shared folder; the files go with the session."""
    spark = pairs.sparkSession
    folder = f"{shared_dir(spark).rstrip('/')}/steps/{uuid.uuid4().hex}"
    where = spark._jvm.org.apache.hadoop.fs.Path(folder)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(where)

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0

        def written() -> pa.RecordBatch:
            keys, values = (np.concatenate([b.column(c).to_numpy() for b in held]) for c in ("key", "ratio"))
            order = np.argsort(keys)
            keys, path = keys[order], f"{folder}/{uuid.uuid4().hex}"
            write_whole(path, keys.tobytes() + values[order].tobytes())
            of, first, count = np.unique(_bucket(keys), return_index=True, return_counts=True)
            return pa.RecordBatch.from_arrays([pa.array([path] * len(of)), *map(pa.array, (of, first, count))], ["path", "bucket", "first", "n"])

        for batch in batches:
            held, n = [*held, batch], n + batch.num_rows
            if n >= 4 * PAIRS_HELD:
                yield written()
                held, n = [], 0
        if n:
            yield written()

    runs: dict[int, list[tuple[str, int, int]]] = {}
    for r in pairs.mapInArrow(write, "path string, bucket long, first long, n long").toArrow().to_pylist():
        runs.setdefault(r["bucket"], []).append((r["path"], r["first"], r["n"]))
    return PairFiles(runs)


def _measured(points: DataFrame, model: ToxicityModel) -> tuple[np.ndarray, np.ndarray]:
    """Classes and measures of the texts that have words."""
    shared = points.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = _WordHashes()
        for whole in batches:
            for batch in text_chunks(whole):
                found = shared.value.measures(batch.column("text").to_pylist(), hashes)
                yield pa.RecordBatch.from_arrays([batch.column("toxic"), *map(pa.array, found.T.copy())], ["toxic", *(f"m{i}" for i in range(found.shape[1]))])

    names = [f"m{i}" for i in range(MEASURES)]
    rows = points.select("toxic", "text").mapInArrow(run, "toxic int, " + ", ".join(f"{n} double" for n in names)).where("m1 > 0").toPandas().sort_values(["toxic", *names])
    return rows["toxic"].to_numpy(float), rows[names].to_numpy()


def learn_toxicity(docs: DataFrame, labels: DataFrame) -> ToxicityModel:
    """Fits the two language models and the calibration on documents (doc_id, text) and labels (doc_id, toxic).

    All labelled documents are used: of PARTS parts one gives the calibration of
    what the others count, then all are counted. Of
    repeated labels the larger holds, others than 0 and 1 are left out. Both
    models are interpolated: a pair backs off to its class's word, whose chance
    comes from how many different words it follows in the class, and that to
    how many it follows in both classes together. Every counted word and pair
    keeps its ratio, rare ones shrunk by the discount; a word that neither
    class has adds nothing. Many pairs are looked up in files. The calibration weighs the mean of the ratios and how
    far the number of words of a high ratio exceeds what ordinary texts of that
    length have, so that length itself says nothing. Of confirmed near copies
    the one of the smallest doc_id counts in each class. Nothing hangs on the
    order of rows. With no labelled
    rows of one class every score is the share of toxic rows.
    """
    chosen = checkpointed(labels.where("toxic in (0, 1) and doc_id is not null").groupBy(F.col("doc_id").alias("chosen_id")).agg(F.max("toxic").cast("int").alias("toxic")))
    total = {r["toxic"]: r["count"] for r in chosen.groupBy("toxic").count().collect()}
    prior = total.get(1, 0) / max(1, sum(total.values()))
    texts = docs.select("doc_id", F.col("text").cast("string").alias("text")).join(small_side(chosen, BROADCAST_LABELS), F.col("doc_id") == F.col("chosen_id"))
    sample = _distinct(texts.select(F.col("chosen_id").alias("doc_id"), "toxic", "text"))
    odds = np.log(max(prior, 1e-6) / max(1 - prior, 1e-6))
    model = ToxicityModel(prior, np.array([odds, *[0.0] * (FEATURES - 1)]))
    counts = lambda rows: rows.groupBy("v", "w").agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1"))
    told = lambda part: sample.where(F.col("part") == part).mapInArrow(_count, "v long, w long, n0 long, n1 long")
    counted = checkpointed(counts(told(0)))
    fitted = _language_models(counted, model)
    if fitted:
        y, found = _measured(sample.where("part = 1"), model)
        if len(set(y)) == 2:
            ordinary = found[y == 0]
            model.usual = (ordinary[:, 2:].sum(axis=0) + 0.5) / (ordinary[:, 1].sum() + 1)
            model.weights = _logistic(model.features(found), y)
        else:
            model.weights[1] = 1.0
        every = checkpointed(counts(counted.unionByName(told(1))))
        _language_models(every, model)
        forget(every)
    forget(chosen, counted, sample)
    return model


def _score(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, hashes = shared.value, _WordHashes()
        for whole in batches:
            for batch in text_chunks(whole):
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(model.scores(batch.column("text").to_pylist(), hashes))], ["doc_id", "score"])

    return run


def score_toxicity(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """(doc_id, score): the calibrated chance that a text is toxic, from its length-normalised log-likelihood ratios.

    A text without words (null, empty, digits only) gets the share of toxic
    labels. Rows are judged alone and in whole; an empty table gives no rows.
    Other columns are ignored.
    """
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(_score(docs.sparkSession.sparkContext.broadcast(model)), "doc_id long, score double")


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    to_learn = table(spark, sf_dir, "labels").where(crc_mod(F.col("doc_id"), 5) != 0)
    scored = score_toxicity(docs, learn_toxicity(docs, to_learn))
    held_out = F.coalesce(crc_mod(F.col("doc_id"), 5) == 0, F.lit(False))
    return scored.select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
