"""Near-duplicate groups by similarity sketches, banding and exact verification."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trainscape.llm._common import checkpointed, connected_components, forget, mix64, salted_join, skew_join, small_side, table, text_chunks

#: At most this many coordinates a band, at least this many bands, and the chance to miss a pair at the threshold.
MOST_ROWS, LEAST_BANDS, MISS = 6, 32, 1e-4
_SIGNED = np.int64


def band_shape(percent: int, miss: float = MISS) -> tuple[int, int]:
    """(rows, bands) of the longest bands that miss two sets of similarity percent / 100 with a chance of at most `miss`.

    32 bands of 6 are enough from 0.80 (6e-5; 0.85: 3e-7) on; lower
    thresholds take shorter bands, the lowest more bands of one coordinate.
    """
    if not 0 < percent <= 100:
        raise ValueError(f"a similarity of {percent} % cannot be searched by bands")
    for rows in range(MOST_ROWS, 0, -1):
        if (1 - (percent / 100) ** rows) ** LEAST_BANDS <= miss:
            return rows, LEAST_BANDS
    return 1, math.ceil(math.log(miss) / math.log(1 - percent / 100))


class _WordHashes(dict):
    """64-bit hashes of words; forgets all when it holds a million."""

    def __missing__(self, word: bytes) -> int:
        if len(self) > 1_000_000:
            self.clear()
        value = self[word] = xxhash.xxh64_intdigest(word)
        return value


def shingle_sets(texts: list[str | None], width: int, hashes: _WordHashes) -> list[np.ndarray]:
    """Sorted distinct hashes of the texts' word shingles (A-Z lower-cased); one for a text of fewer words, none without words."""
    found = []
    for text in texts:
        words = text.encode("utf-8", "surrogatepass").lower().split() if text else []
        ids = np.fromiter(map(hashes.__getitem__, words), np.uint64, len(words))
        span = min(width, len(ids))
        mixed = np.full(max(len(ids) - span + 1, 0) if span else 0, span, np.uint64)
        for k in range(span):
            mixed = mix64(mixed * np.uint64(0x9E3779B97F4A7C15) + ids[k : k + len(mixed)])
        found.append(np.unique(mixed))
    return found


def similarity_sketches(sets: list[np.ndarray], bins: int) -> np.ndarray:
    """One row of `bins` values per set, filled in rounds of hashed bin placement.

    In round i < bins every element falls into a hashed bin with the value
    (i, hash), in round bins + j all elements fall into bin j, so each bin is
    full at the end; a set's rounds stop as soon as its bins are full. Earlier
    rounds win, then smaller hashes. Empty sets keep the largest value.
    """
    full = np.iinfo(np.uint64).max
    out = np.full((len(sets), bins), full, np.uint64)
    owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    items = np.concatenate(sets) if sets else np.empty(0, np.uint64)
    flat = out.reshape(-1)
    for turn in range(2 * bins):
        if not len(items):
            break
        mixed = mix64(items ^ mix64(np.full(1, turn + 1, np.uint64)))
        where = ((mixed >> np.uint64(32)) * np.uint64(bins) >> np.uint64(32)).astype(np.int64) if turn < bins else turn - bins
        np.minimum.at(flat, owner * bins + where, (np.uint64(turn) << np.uint64(32)) | (mixed & np.uint64(0xFFFFFFFF)))
        open_sets = (out == full).any(axis=1)
        still = open_sets[owner]
        if not still.all():
            owner, items = owner[still], items[still]
    return out


def band_keys(sketches: np.ndarray, rows: int, bands: int) -> np.ndarray:
    parts = sketches.reshape(len(sketches), bands, rows)
    keys = np.broadcast_to(np.arange(1, bands + 1, dtype=np.uint64), (len(sketches), bands)).copy()
    for k in range(rows):
        keys = mix64(keys * np.uint64(0x9E3779B97F4A7C15) + parts[:, :, k])
    return keys.view(_SIGNED)


def _sketch(width: int, rows: int, bands: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = _WordHashes()
        for whole in batches:
            for batch in text_chunks(whole):
                sets = shingle_sets(batch.column("text").to_pylist(), width, hashes)
                keys = band_keys(similarity_sketches(sets, rows * bands), rows, bands)
                digests = [xxhash.xxh3_128_digest(s.tobytes()) for s in sets]
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id"), pa.array([len(s) for s in sets], pa.int64()), pa.array(digests, pa.binary()), pa.array(list(keys), pa.list_(pa.int64()))],
                    ["doc_id", "n_shingles", "digest", "bands"],
                )

    return run


def _compare(width: int, percent: int):
    """Adds to pairs of texts whether they are linked, the size of a's set, and what b's set adds to it and leaves out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, last, held = _WordHashes(), None, None
        for whole in batches:
            for batch in text_chunks(whole, "text_b"):
                linked, size, added, left = [], [], [], []
                for i, a in enumerate(batch.column("a").to_pylist()):
                    text = batch.column("text_a")[i].as_py()
                    if (a, text) != last:
                        last, held = (a, text), shingle_sets([text], width, hashes)[0]
                    other = shingle_sets([batch.column("text_b")[i].as_py()], width, hashes)[0]
                    more, less = np.setdiff1d(other, held, assume_unique=True), np.setdiff1d(held, other, assume_unique=True)
                    common = len(held) - len(less)
                    linked.append(bool(common) and 100 * common >= percent * (len(held) + len(more)))
                    size.append(len(held))
                    added.append(more.view(_SIGNED))
                    left.append(less.view(_SIGNED))
                yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b"), pa.array(linked, pa.bool_()), pa.array(size, pa.int64()), pa.array(added, pa.list_(pa.int64())), pa.array(left, pa.list_(pa.int64()))], ["a", "b", "linked", "size", "added", "missing"])

    return run


def _compared(pairs: DataFrame, texts: DataFrame, width: int, percent: int) -> DataFrame:
    """(a, b, linked, size, added, missing) of pairs, on their full sets; an a of very many pairs is dealt out."""
    ids = checkpointed(pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct())
    wanted = texts.join(small_side(ids), "id", "left_semi")
    left = wanted.select(F.col("id").alias("b"), F.col("text").alias("text_b")).join(small_side(pairs), "b")
    both = salted_join(left, wanted.select(F.col("id").alias("a"), F.col("text").alias("text_a")), ["a"], "b", pairs).select("a", "b", "text_a", "text_b")
    tested = checkpointed(both.mapInArrow(_compare(width, percent), "a long, b long, linked boolean, size long, added array<long>, missing array<long>"))
    forget(ids)
    return tested


def _stars(banded: DataFrame, total: int) -> DataFrame:
    """(a, b): every member b of a band with the band's hub a, the member whose bands have most members in all."""
    sizes = checkpointed(banded.groupBy("key").agg(F.count("*").alias("n")).where("n > 1"))
    shared = checkpointed(skew_join(banded, sizes, ["key"], "n", total))
    weight = shared.groupBy("id").agg(F.sum("n").alias("weight"))
    rank = F.col("weight") * 1_048_576 + F.pmod(F.xxhash64("id"), F.lit(1_048_576))
    hubs = checkpointed(shared.join(weight, "id").groupBy("key").agg(F.max_by("id", rank).alias("a"), F.max("n").alias("n")))
    stars = checkpointed(skew_join(shared.drop("n"), hubs, ["key"], "n", total).where("id <> a").select("a", F.col("id").alias("b")).distinct())
    forget(sizes, shared, hubs)
    return stars


def _judged(pairs: DataFrame, members: DataFrame, percent: int) -> DataFrame:
    """(a, b): the linked ones of pairs (star, x, y), by what x and y share of their differences from the hub."""
    sides = [members.select("star", *(F.col(c).alias(f"{c}{i}") for c in ("differences", "cost")), F.col("b").alias(i), *(["room"] if i == "x" else [])) for i in "xy"]
    pairs = checkpointed(pairs)
    both = salted_join(sides[1].join(small_side(pairs), ["star", "y"]), sides[0], ["star", "x"], "y", pairs)
    same = F.size(F.array_intersect("differencesx", "differencesy"))
    linked = checkpointed(both.where((100 + percent) * same >= F.col("costx") + F.col("costy") - F.col("room")).select(F.col("x").alias("a"), F.col("y").alias("b")).distinct())
    forget(pairs)
    return linked


def _within_stars(tested: DataFrame, percent: int) -> DataFrame:
    """(a, b): links between members of one hub's star that join what links to hubs leave apart.

    A member that adds n elements to the hub's set of h and leaves out d costs
    p n + 100 d. Two members that share s of their differences are linked if
    and only if (100 + p) s >= their costs - (100 - p) h; one is linked to the
    hub if its cost is at most (100 - p) h = room. So of a pair that links to
    hubs leave apart one costs more than room, and s has a lower bound for the
    cheaper member (its cost, and a partner of no less) and one for the dearer
    (s >= (cost - room) / 100, as a partner costs at least p s). By these
    bounds and with rare elements first, a short list of the cheaper one's
    differences meets a long list of the dearer one's, so elements that mark
    the hub and are shared by all are in no short list.

    First the members of each element's short lists are compared with the
    cheapest of them. Of the components that result, the largest of each star
    needs no comparisons within; the members outside it are compared with all
    that their lists meet in other components.
    """
    per_star = tested.groupBy("a").agg(F.count("*").alias("n"), F.min("linked").alias("whole")).where("n > 1 and not whole").select("a")
    rows = tested.join(small_side(checkpointed(per_star)), "a", "left_semi")
    cost = F.size("added") * percent + F.size("missing") * 100
    members = checkpointed(rows.select(F.col("a").alias("star"), "b", "linked", cost.cast("long").alias("cost"), ((100 - percent) * F.col("size")).alias("room"), F.concat("added", "missing").alias("differences")))
    known = ["star", "b", "linked", "cost", "room"]
    each = members.select(*known, F.explode("differences").alias("e"))
    often = checkpointed(each.groupBy("star", "e").agg(F.count("*").alias("n")))
    total = often.agg(F.sum("n")).first()[0] or 0
    if not total:
        return checkpointed(tested.where("false").select("a", "b"))
    ranked = skew_join(each, often, ["star", "e"], "n", total).groupBy(*known).agg(F.sort_array(F.collect_list(F.struct("n", "e"))).alias("es"))

    def listed(bound) -> DataFrame:
        return F.filter(F.slice("es", 1, F.greatest(F.size("es") - F.greatest(F.ceil(bound), F.lit(1)) + 1, F.lit(0)).cast("int")), lambda x: x["n"] > 1)["e"]

    cheap = (F.col("cost") + F.greatest(F.col("cost"), F.col("room") + 1) - F.col("room")) / (100 + percent)
    lists = checkpointed(ranked.select("star", "b", "linked", "cost", listed(cheap).alias("short"), F.when(~F.col("linked"), listed((F.col("cost") - F.col("room")) / 100)).alias("long")))

    short = lists.select("star", "b", "linked", "cost", F.explode("short").alias("e"))
    centre = checkpointed(short.groupBy("star", "e").agg(F.min_by(F.struct(F.col("b").alias("x"), F.col("linked").alias("linkedx")), F.struct("cost", "b")).alias("c"), F.count("*").alias("n")).where("n > 1").select("star", "e", "c.*", "n"))
    beside = skew_join(short, centre, ["star", "e"], "n", total).where("b <> x and not (linked and linkedx)")
    first = _judged(beside.select("star", "x", F.col("b").alias("y")).distinct(), members, percent)

    joined = connected_components(members.where("linked").select(F.col("star").alias("a"), "b").unionByName(first))
    placed = checkpointed(lists.join(joined.withColumnRenamed("node", "b"), "b", "left").withColumn("component", F.coalesce("component", "b")))
    parts = placed.groupBy("star", "component").agg(F.count("*").alias("n")).groupBy("star").agg(F.max_by("component", F.struct("n", "component")).alias("main"), F.sum("n").alias("n"))
    parts = checkpointed(parts)
    sided = checkpointed(skew_join(placed, parts, ["star"], "n", parts.agg(F.sum("n")).first()[0] or 0).withColumn("apart", F.col("component") != F.col("main")))
    dear = sided.select("star", F.col("b").alias("y"), F.col("cost").alias("costy"), F.col("component").alias("componenty"), F.col("apart").alias("aparty"), F.explode("long").alias("e"))
    low = sided.select("star", F.col("b").alias("x"), F.col("cost").alias("costx"), F.col("component").alias("componentx"), "apart", F.explode("short").alias("e"))
    met = dear.where("aparty").join(low.drop("apart"), ["star", "e"]).drop("aparty").unionByName(dear.where("not aparty").drop("aparty").join(low.where("apart").drop("apart"), ["star", "e"]))
    met = met.where("componentx <> componenty and (costx < costy or (costx = costy and x < y))").select("star", "x", "y").distinct()
    second = _judged(met, members, percent)
    links = checkpointed(first.unionByName(second))
    forget(members, often, lists, centre, first, second, joined, placed, parts, sided)
    return links


def near_dedup(docs: DataFrame, width: int = 5, percent: int = 80, rows: int | None = None, bands: int | None = None) -> DataFrame:
    """Groups of near-duplicate documents: (doc_id, n_shingles, component_id, kept).

    Words are split at ASCII white space with A-Z lower-cased; a document's set
    holds its distinct `width`-word shingles. Documents whose sets overlap by
    `percent` of their union or more are linked; component_id is the smallest
    doc_id reachable over links.

    Equal sets form one class, of which only the smallest doc_id goes on.
    Classes that share a band are compared with the band's hub (of equals, the
    one of the larger hash); members that stay apart are compared where their
    differences from the hub allow a link (an exact bound), so members of a
    band get the components that all their links would give. Every link is
    exact on the full sets. Bands follow the threshold (`band_shape`) unless
    rows and bands are given.

    Null, empty and wordless texts have an empty set and are linked with
    nothing; texts of any length are taken whole. Rows without a doc_id stay
    alone (component_id null, kept). Rows with one doc_id and different texts
    share a node. An empty table gives no rows. Other columns are ignored.
    """
    fit_rows, fit_bands = band_shape(percent)
    rows, bands = rows or fit_rows, bands or fit_bands
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    sketched = checkpointed(docs.mapInArrow(_sketch(width, rows, bands), "doc_id long, n_shingles long, digest binary, bands array<long>"))
    real = sketched.where("doc_id is not null and n_shingles > 0")
    classes = checkpointed(real.groupBy("digest", "n_shingles").agg(F.min("doc_id").alias("head"), F.count("*").alias("n")))
    total = classes.agg(F.sum("n")).first()[0] or 0

    heads = real.join(small_side(classes.select(F.col("head").alias("doc_id"))), "doc_id", "left_semi")
    banded = checkpointed(heads.select(F.col("doc_id").alias("id"), F.explode("bands").alias("key")))
    stars = _stars(banded, total)
    forget(banded)
    texts = docs.where("doc_id is not null").select(F.col("doc_id").alias("id"), "text")
    tested = _compared(stars, texts, width, percent)
    within = _within_stars(tested, percent)
    links = tested.where("linked").select("a", "b").unionByName(within)

    member = checkpointed(skew_join(real.select("doc_id", "digest", "n_shingles"), classes, ["digest", "n_shingles"], "n", total).select("doc_id", "n_shingles", "head", "n"))
    several = member.groupBy("doc_id").agg(F.collect_set("head").alias("heads")).where(F.size("heads") > 1)
    links = links.unionByName(several.select(F.array_min("heads").alias("a"), F.explode("heads").alias("b")))
    found = connected_components(links)
    named = checkpointed(member.groupBy("head").agg(F.count("*").alias("n")).join(found.withColumnRenamed("node", "head"), "head", "left").select("head", "n", F.coalesce("component", "head").alias("component")))
    placed = checkpointed(skew_join(member.drop("n"), named, ["head"], "n", total).select("doc_id", "n_shingles", "component"))
    forget(classes, stars, tested, within, found, member, named)

    wordless = sketched.where("doc_id is not null and n_shingles = 0").select("doc_id", "n_shingles")
    wordless = wordless.join(placed.where("component <> doc_id").select("doc_id", "component").distinct(), "doc_id", "left")
    nameless = sketched.where("doc_id is null").select("doc_id", "n_shingles", F.col("doc_id").alias("component"))
    component = F.coalesce("component", "doc_id")
    out = checkpointed(placed.unionByName(wordless).unionByName(nameless))
    forget(sketched, placed)
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def op1_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup(table(spark, sf_dir, "documents"), width=3, percent=85)
