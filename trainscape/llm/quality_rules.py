"""Quality rules run as a short-circuit cascade, ordered by rejections per cost."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trainscape.llm._common import mix64, table, text_chunks
from trainscape.llm.near_dedup import _WordHashes

BLANK = " \t\n\r\x0b\x0c"
SYMBOLS = "#*$%&|<>"
#: Distinct words are counted in stretches of this many words, so that a text's length does not matter.
STRETCH = 100
#: Rows on which costs and selectivities are estimated; they decide the order only, never a verdict.
SAMPLE_ROWS = 512


class Measures:
    """Lazy measures of one text; each is computed at most once, when a rule asks for it."""

    def __init__(self, text: str | None, hashes: _WordHashes):
        self.text, self._hashes, self._kept = text or "", hashes, {}

    def __getattr__(self, name: str):
        if name.startswith("_") or name not in _MEASURES:
            raise AttributeError(name)
        if name not in self._kept:
            self._kept[name] = _MEASURES[name](self)
        return self._kept[name]


def _repeat_words(m: Measures, width: int = 5) -> int:
    """Words inside a window of `width` words that occurs at least twice in the text."""
    n = len(m.words)
    if n <= width:
        return 0
    ids = np.fromiter(map(m._hashes.__getitem__, m.words), np.uint64, n)
    windows = np.zeros(n - width + 1, np.uint64)
    for k in range(width):
        windows = mix64(windows * np.uint64(0x9E3779B97F4A7C15) + ids[k : k + len(windows)])
    _, inverse, counts = np.unique(windows, return_inverse=True, return_counts=True)
    twice = counts[inverse] > 1
    covered = np.zeros(n + 1, np.int64)
    covered[:-width] += twice
    covered[width:] -= twice
    return int((np.cumsum(covered)[:n] > 0).sum())


def _dup_lines(m: Measures) -> int:
    return len(m.lines) - len(set(m.lines))


_MEASURES: dict[str, Callable[[Measures], object]] = {
    "words": lambda m: m.text.encode("utf-8", "surrogatepass").split(),
    "n_words": lambda m: len(m.words),
    "word_chars": lambda m: len(m.text) - sum(map(m.text.count, BLANK)),
    "n_symbols": lambda m: sum(map(m.text.count, SYMBOLS)),
    "lines": lambda m: [x for x in m.text.split("\n") if x.strip(BLANK)],
    "n_lines": lambda m: len(m.lines),
    "n_dup_lines": _dup_lines,
    "n_repeat_words": _repeat_words,
    "n_marks": lambda m: m.text.count("!") + m.text.count("?"),
    "n_fresh": lambda m: sum(len(set(m.words[i : i + STRETCH])) for i in range(0, len(m.words), STRETCH)),
}


@dataclass(frozen=True)
class Rule:
    """A named test that is true where a text is to be rejected; `sql` says the same over the measures."""

    name: str
    rejects: Callable[[Measures], bool]
    sql: str


RULES = (
    Rule("too_short", lambda m: m.n_words < 10, "n_words < 10"),
    Rule("repetitive", lambda m: 100 * m.n_repeat_words > 20 * m.n_words, "100 * n_repeat_words > 20 * n_words"),
    Rule("symbols", lambda m: 10 * m.n_symbols > m.n_words, "10 * n_symbols > n_words"),
    Rule("word_length", lambda m: not 3 * m.n_words <= m.word_chars <= 10 * m.n_words, "word_chars < 3 * n_words or word_chars > 10 * n_words"),
    Rule("dup_lines", lambda m: 10 * m.n_dup_lines > 4 * m.n_lines, "10 * n_dup_lines > 4 * n_lines"),
    Rule("marks", lambda m: 4 * m.n_marks > m.n_words, "4 * n_marks > n_words"),
    Rule("few_distinct", lambda m: 5 * m.n_fresh < m.n_words, "5 * n_fresh < n_words"),
)
BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def _profile(rules: tuple[Rule, ...]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = _WordHashes()
        spent, hits, rows = dict.fromkeys((r.name for r in rules), 0.0), dict.fromkeys((r.name for r in rules), 0), 0
        for batch in batches:
            for text in batch.column("text").to_pylist():
                rows += 1
                for rule in rules:
                    began = time.perf_counter()
                    hits[rule.name] += bool(rule.rejects(Measures(text, hashes)))
                    spent[rule.name] += time.perf_counter() - began
        yield pa.RecordBatch.from_pylist([{"rule": r.name, "seconds": spent[r.name], "hits": hits[r.name], "n": rows} for r in rules], pa.schema([("rule", pa.string()), ("seconds", pa.float64()), ("hits", pa.int64()), ("n", pa.int64())]))

    return run


def plan_cascade(docs: DataFrame, rules: tuple[Rule, ...] = RULES, sample_rows: int = SAMPLE_ROWS) -> list[Rule]:
    """The rules in the order of their rejections per second on a sample of at most sample_rows rows."""
    sample = docs.select(F.col("text").cast("string").alias("text")).sample(0.1, seed=11).limit(sample_rows)
    seen = {r["rule"]: r for r in sample.mapInArrow(_profile(rules), "rule string, seconds double, hits long, n long").groupBy("rule").agg(F.sum("seconds").alias("seconds"), F.sum("hits").alias("hits"), F.sum("n").alias("n")).collect()}
    worth = {r.name: (seen[r.name]["hits"] + 0.1) / (seen[r.name]["seconds"] + 1e-6) if r.name in seen else 0.0 for r in rules}
    return sorted(rules, key=lambda r: -worth[r.name])


def _cascade(ordered: list[Rule], measures: tuple[str, ...]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = _WordHashes()
        for whole in batches:
            for batch in text_chunks(whole):
                verdicts, columns = [], [[] for _ in measures]
                for text in batch.column("text").to_pylist():
                    m = Measures(text, hashes)
                    verdicts.append(next((r.name for r in ordered if r.rejects(m)), None))
                    for name, column in zip(measures, columns):
                        column.append(getattr(m, name))
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(verdicts, pa.string()), *(pa.array(c, pa.int64()) for c in columns)], ["doc_id", "rejected_by", *measures])

    return run


def quality_cascade(docs: DataFrame, rules: tuple[Rule, ...] = RULES, measures: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, rejected_by, *measures): the first rule of the cascade that rejects each text, or null.

    Costs and selectivities are estimated on a bounded sample; texts that a
    rule rejects are not shown to later rules. The order never changes which
    texts are kept, only which rule is named. Null and empty texts have no
    words and fail the length rule; whole texts of any length are measured. Each
    row is judged alone, so repeated rows and ids give repeated results; an
    empty table gives none. Other columns are ignored.
    """
    ordered = plan_cascade(docs, rules)
    schema = ", ".join(["doc_id long", "rejected_by string", *(f"{m} long" for m in measures)])
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(_cascade(ordered, measures), schema)


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = quality_cascade(table(spark, sf_dir, "documents"), measures=BASE)
    failed = F.expr("n_words < 10 or 100 * n_repeat_words > 20 * n_words")
    return judged.select("doc_id", *BASE, failed.alias("base_failed"), (~failed & F.col("rejected_by").isNull()).alias("kept"))


OP2_SQL = r"""
with w as (select doc_id, coalesce(text, '') as text, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') as words,
                  list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) as lines from documents),
 g as (select doc_id, unnest(range(1, len(words) - 3)) as i, words from w where len(words) > 4),
 h as (select doc_id, i, count(*) over (partition by doc_id, words[i], words[i+1], words[i+2], words[i+3], words[i+4]) as n from g),
 r as (select doc_id, count(distinct i + k) as n_repeat_words from h, (select unnest(range(0, 5)) as k) where n > 1 group by doc_id),
 m as (select w.doc_id, len(words)::bigint as n_words, coalesce(list_sum(list_transform(words, lambda x: length(x))), 0)::bigint as word_chars,
              (length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')))::bigint as n_symbols,
              (len(lines) - len(list_distinct(lines)))::bigint as n_dup_lines, coalesce(n_repeat_words, 0)::bigint as n_repeat_words,
              len(lines) as n_lines, length(text) - length(regexp_replace(text, '[!?]', '', 'g')) as n_marks, len(list_distinct(list_transform(words, lambda x, i: ((i - 1) // 100)::varchar || ' ' || x))) as n_fresh
       from w left join r using (doc_id))
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
       n_words < 10 or 100 * n_repeat_words > 20 * n_words as base_failed, not (""" + " or ".join(f"({r.sql})" for r in RULES) + """) as kept
from m"""
