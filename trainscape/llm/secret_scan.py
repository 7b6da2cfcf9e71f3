"""Secrets in texts: fixed patterns, and strings that stay incompressible beside their surroundings."""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left, bisect_right
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trainscape.llm._common import table, text_chunks

KINDS = ("assign", "access", "hex", "novel")
_ASSIGN = re.compile(r"""(?ai)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
_ACCESS = re.compile(r"AKIA[A-Z0-9]+")
_HEX = re.compile(r"[0-9a-f]{24,}")
_NAMES = ("password", "passwd", "secret", "token", "apikey", "api_key")

#: Words that make their surroundings sensitive; a candidate starts within REACH characters after one or ends within REACH before one, or adjoins a found span.
SENSITIVE = ("access", "api", "auth", "bearer", "credential", "key", "passphrase", "passwd", "password", "private", "pwd", "secret", "signature", "token")
REACH, CONTEXT = 48, 512
_SENSITIVE = re.compile("(?ai)" + "|".join(SENSITIVE))
_CANDIDATE = re.compile(r"(?a)[A-Za-z0-9+/_=-]{16,}")
#: What may lie between the parts of one secret (line ends, dots, quotes, comment marks), and the short last line of an armoured key.
_JOINT = re.compile(r"""[\s\\.,:;|"'+>#*-]{0,24}""")
_LAST_LINE = re.compile(r"(?a)(?:\s|\\[nr]){1,24}([A-Za-z0-9+/=]{1,15})(?=(?:\s|\\[nr]){0,24}-----END)")
LEAST = 16
#: Identifiers and words that code and prose are full of; the dictionary starts with them.
IDENTIFIERS = b"abcdefghijklmnopqrstuvwxyz ABCDEFGHIJKLMNOPQRSTUVWXYZ 0123456789 http://www. https:// .com/ .org/ .json .html import return function const static public private void string class self.config value default username user_name account client_id customer request response authorization content-type application example environment variable example_token your_api_key changeme placeholder access_token refresh_token secret_key api_key password token private_key "
#: Compressed bytes that a candidate adds per character, from which it counts as new.
NOVELTY = 0.75


def novelty(candidate: str, before: str, after: str, identifiers: bytes = IDENTIFIERS) -> float:
    """Compressed bytes that a candidate adds to its surroundings, per byte of it."""
    data = candidate.encode("utf-8", "surrogatepass")
    primer = identifiers + (after + " " + before).encode("utf-8", "surrogatepass")
    packer = zstandard.ZstdCompressor(level=9, dict_data=zstandard.ZstdCompressionDict(primer, dict_type=zstandard.DICT_TYPE_RAWCONTENT), write_checksum=False, write_content_size=False, write_dict_id=False)
    return (len(packer.compress(data)) - len(packer.compress(b""))) / len(data)


def base_spans(text: str, low: str) -> list[tuple[int, int, int]]:
    """(start, kind's place in KINDS, end) of the fixed patterns, sorted."""
    found = []
    if any(n in low for n in _NAMES):
        found += [(m.start(), 0, m.end()) for m in _ASSIGN.finditer(text) if len(m[2]) >= 6]
    if "AKIA" in text:
        found += [(m.start(), 1, m.end()) for m in _ACCESS.finditer(text) if len(m[0]) >= 20]
    found += [(m.start(), 2, m.end()) for m in _HEX.finditer(text)]
    return sorted(found)


def _pieces(text: str, cuts: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Candidates less the cut spans (sorted by start), where long enough."""
    found, first = [], 0
    for m in _CANDIDATE.finditer(text):
        at, end = m.span()
        while first < len(cuts) and cuts[first][1] <= at:
            first += 1
        k = first
        while k < len(cuts) and cuts[k][0] < end:
            if cuts[k][0] - at >= LEAST:
                found.append((at, cuts[k][0]))
            at = max(at, cuts[k][1])
            k += 1
        if end - at >= LEAST:
            found.append((at, end))
    return found


def _merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for s, e in sorted(spans):
        if out and s <= out[-1][1]:
            out[-1] = (out[-1][0], max(e, out[-1][1]))
        else:
            out.append((s, e))
    return out


def novel_spans(text: str, low: str, taken: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """Incompressible strings with digits near a sensitive word or adjoining a found span, apart from what is taken."""
    if not taken and not any(s in low for s in SENSITIVE):
        return []
    words = [m.span() for m in _SENSITIVE.finditer(text)]
    base = _merged([(s, e) for s, _, e in taken])
    pieces = _pieces(text, _merged([*words, *base]))
    if not pieces:
        return []
    starts, ends = [s for s, _ in words], [e for _, e in words]

    def near(start: int, end: int) -> bool:
        k = bisect_right(ends, start)
        if k and start - ends[k - 1] <= REACH:
            return True
        k = bisect_left(starts, end)
        return k < len(starts) and starts[k] - end <= REACH

    def new(start: int, end: int) -> bool:
        string = text[start:end]
        return any(c.isdigit() for c in string) and any(c.isalpha() for c in string) and novelty(string, text[max(0, start - CONTEXT) : start], text[end : end + CONTEXT]) >= NOVELTY

    fixed, parts = set(base), sorted({*base, *pieces})
    tried = {p: new(*p) for p in pieces if near(*p)}
    # context passes to the next part and, on the way back, to the one before
    for order in (parts, parts[::-1]):
        for one, other in zip(order, order[1:]):
            gap = text[min(one[1], other[1]) : max(one[0], other[0])]
            if (one in fixed or tried.get(one)) and other not in fixed and other not in tried and _JOINT.fullmatch(gap):
                tried[other] = new(*other)
    found = [p for p, yes in tried.items() if yes]
    last = [m.span(1) for m in (_LAST_LINE.match(text, end) for _, end in found) if m]
    last = [p for p in last if not any(p[0] < e and s < p[1] for s, e in base)]
    return [(s, 3, e) for s, e in sorted({*found, *last})]


def find_secrets(text: str | None) -> list[tuple[int, int, int]]:
    """(start, kind's place in KINDS, end) in code points, end exclusive, by start and then kind."""
    if not text:
        return []
    low = text.lower()
    base = base_spans(text, low)
    return sorted(base + novel_spans(text, low, base))


def spans_text(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


def redact(text: str | None, spans: list[tuple[int, int, int]]) -> str | None:
    """The text with every span replaced by its kind in angle brackets; of overlapping spans the first stands for all."""
    if not spans:
        return text
    out, at = [], 0
    for s, k, e in spans:
        if s >= at:
            out += [text[at:s], f"<{KINDS[k]}>"]
        at = max(at, e)
    return "".join([*out, text[at:]])


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for batch in text_chunks(whole):
            found = [find_secrets(t) for t in batch.column("text").to_pylist()]
            counts = [pa.array([sum(k == kind for _, k, _ in spans) for spans in found], pa.int64()) for kind in range(3)]
            digests = [hashlib.sha256(spans_text([s for s in spans if s[1] < 3]).encode()).hexdigest() for spans in found]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *counts, pa.array(digests), pa.array([spans_text(s) for s in found])], ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"])


def scan_secrets(docs: DataFrame) -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, base_sha256, spans) of every whole text.

    spans lists kind:start:end of assignments, access keys and long hexadecimal
    strings, and of `novel` strings: at least 16 characters in a sensitive
    context (a sensitive word within 48 characters before or after, or a found
    span beside it, as in the lines of a key), less the parts that other spans
    or sensitive words take, with letters and digits, and adding nearly as many compressed bytes as they are long to a
    dictionary of identifiers and of the text around them. Null and empty texts
    have none. Rows are judged alone; other columns are ignored.
    """
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(_scan, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")


def _redact(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for batch in text_chunks(whole):
            place = batch.schema.get_field_index("text")
            texts = [redact(t, find_secrets(t)) for t in batch.column(place).to_pylist()]
            yield batch.set_column(place, batch.schema.field(place), pa.array(texts, batch.schema.field(place).type))


def redact_secrets(docs: DataFrame) -> DataFrame:
    """The documents with every secret in text replaced by its kind; other columns stay."""
    return docs.mapInArrow(_redact, docs.schema)


def op8_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_secrets(table(spark, sf_dir, "documents"))
