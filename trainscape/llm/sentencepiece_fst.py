"""SentencePiece encoding and decoding as shortest paths through a weighted transducer."""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trainscape.llm._common import table, text_chunks

SPACE = "▁"
# Fixed values of the model format: model types and piece types.
UNIGRAM, BPE = 1, 2
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
#: Entries of the memo of paths through parts of words, and of pairs of pieces; a full memo starts anew.
MEMO = 500_000


def default_model() -> bytes:
    """The public 32,000-piece model of this machine, read where the job is planned."""
    import public_tokenizers

    with open(public_tokenizers.path("piece_bpe_32k.model"), "rb") as f:
        return f.read()


class _Memo(dict):
    def __init__(self, make):
        super().__init__()
        self._make = make

    def __missing__(self, key):
        if len(self) >= MEMO:
            self.clear()
        value = self[key] = self._make(key)
        return value


@dataclass
class Transducer:
    """The composition of normaliser, pieces and byte fallback, without its input.

    The normaliser rewrites a space as the space mark and puts one in front.
    Arcs of the piece transducer read a piece's characters and write its id; a
    character that no piece spells alone is read by an arc that writes the ids
    of its UTF-8 bytes. An arc of a unigram model weighs minus its score.
    In a BPE model two arcs may follow each other only if merging their joined
    text by score gives just these two pieces, other pairs weigh infinity; the
    merged text of any input is the one path of finite weight.
    """

    kind: int
    scores: dict[str, float]
    ids: dict[str, int]
    byte_ids: list[int]
    unknown: int
    outputs: list[bytes]
    prefix: bool = True
    longest: int = 1
    joints: set[str] = field(default_factory=set)
    reach: dict[str, int] = field(default_factory=dict)

    @classmethod
    def compile(cls, model: bytes) -> Transducer:
        from sentencepiece import sentencepiece_model_pb2 as pb

        proto = pb.ModelProto()
        proto.ParseFromString(model)
        spec = proto.normalizer_spec
        if proto.trainer_spec.model_type not in (UNIGRAM, BPE):
            raise ValueError("only unigram and BPE models have a piece transducer")
        if spec.precompiled_charsmap or spec.remove_extra_whitespaces or not spec.escape_whitespaces or proto.trainer_spec.treat_whitespace_as_suffix:
            raise ValueError("only the identity normaliser that keeps and escapes white space is compiled")
        scores, ids, outputs, byte_ids, unknown = {}, {}, [], [-1] * 256, 0
        for i, p in enumerate(proto.pieces):
            if p.type in (NORMAL, USER):
                scores[p.piece], ids[p.piece] = p.score, i
                outputs.append(p.piece.replace(SPACE, " ").encode())
            elif p.type == BYTE:
                byte_ids[int(p.piece[3:5], 16)] = i
                outputs.append(bytes([int(p.piece[3:5], 16)]))
            else:
                unknown = i if p.type == UNKNOWN else unknown
                outputs.append(" ⁇ ".encode() if p.type == UNKNOWN else b"")
        made = cls(proto.trainer_spec.model_type, scores, ids, byte_ids, unknown, outputs, spec.add_dummy_prefix)
        made.longest = max(map(len, ids), default=1)
        for p in ids:
            made.reach[p[:2]] = max(made.reach.get(p[:2], 1), len(p))
        made.joints = {p[i : i + 2] for p in ids for i in range(len(p) - 1)}
        return made

    def __post_init__(self):
        self.fallback = min(self.scores.values(), default=0.0) - 10
        self._start()

    def _start(self) -> None:
        self._whole, self._part = _Memo(self._encode_chunk), _Memo(self._encode_part)
        self._pairs = _Memo(lambda pair: self._merge("".join(pair)) == list(pair))
        self._chunks = re.compile(f"{SPACE}*[^{SPACE}\\n]+|{SPACE}+|\\n")

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if not k.startswith("_")}

    def __setstate__(self, state):
        self.__dict__.update(state)
        self._start()

    def _merge(self, text: str) -> list[str]:
        """The text merged pair by pair, the highest score first, of equals the leftmost."""
        parts = list(text)
        while len(parts) > 1:
            best, at = -np.inf, -1
            for i in range(len(parts) - 1):
                score = self.scores.get(parts[i] + parts[i + 1])
                if score is not None and score > best:
                    best, at = score, i
            if at < 0:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    def _path_bpe(self, text: str) -> list[str]:
        """The one path whose neighbours may all follow each other: depth first, longest arcs first, dead ends remembered."""
        n, ids, pairs, reach = len(text), self.ids, self._pairs, self.reach
        out: list[str] = []
        dead: set[int] = set()
        at, length = 0, min(reach.get(text[:2], 1), n)
        while at < n:
            before = out[-1] if out else None
            while length:
                piece = text[at : at + length]
                if (length == 1 or piece in ids) and at + length not in dead and (before is None or pairs[before, piece]):
                    break
                length -= 1
            if length:
                out.append(piece)
                at += length
                length = min(reach.get(text[at : at + 2], 1), n - at)
            else:
                dead.add(at)
                if not out:
                    return self._merge(text)
                length = len(out.pop())
                at -= length
        return out

    def _path_unigram(self, text: str) -> list[str]:
        """The path of least total weight; of equal ones that with the longer last pieces."""
        n, scores = len(text), self.scores
        best, cut = [0.0] + [np.inf] * n, [0] * (n + 1)
        for end in range(1, n + 1):
            for start in range(max(0, end - self.longest), end):
                score = scores.get(text[start:end], self.fallback if end - start == 1 else None)
                if score is not None and best[start] - score < best[end]:
                    best[end], cut[end] = best[start] - score, start
        out, at = [], n
        while at:
            out.append(text[cut[at] : at])
            at = cut[at]
        return out[::-1]

    def _written(self, pieces: list[str]) -> bytes:
        """The ids that a path writes, four bytes each."""
        out: list[int] = []
        for p in pieces:
            i = self.ids.get(p)
            if i is not None:
                out.append(i)
            else:
                data = [self.byte_ids[b] for b in p.encode("utf-8", "replace")]
                out += [self.unknown] if -1 in data else data
        return np.asarray(out, np.int32).tobytes()

    def _encode_part(self, text: str) -> bytes:
        return self._written(self._path_bpe(text) if self.kind == BPE else self._path_unigram(text))

    def _encode_chunk(self, chunk: str) -> bytes:
        """A chunk is cut where no piece spans two neighbours; every path passes there, so the parts' paths join."""
        blanks = len(chunk) - len(chunk.lstrip(SPACE))
        if self.kind == BPE and blanks > 1:
            first = self._path_bpe(self._first_part(chunk[blanks - 1 :]))[0] if blanks < len(chunk) else ""
            taken = len(first) > 1
            run = self._merge(chunk[: blanks - taken])
            return self._written(run) + (self._whole[chunk[blanks - 1 :]] if taken else self._whole[chunk[blanks:]] if blanks < len(chunk) else b"")
        start, out, joints = 0, [], self.joints
        for i in range(1, len(chunk)):
            if chunk[i - 1 : i + 1] not in joints:
                out.append(self._part[chunk[start:i]])
                start = i
        return b"".join([*out, self._part[chunk[start:]]])

    def _first_part(self, chunk: str) -> str:
        return chunk[: next((i for i in range(1, len(chunk)) if chunk[i - 1 : i + 1] not in self.joints), len(chunk))]

    def encode(self, text: str) -> np.ndarray:
        if not text:
            return np.empty(0, np.int32)
        text = ((" " if self.prefix else "") + text).replace(" ", SPACE)
        return np.frombuffer(b"".join(map(self._whole.__getitem__, self._chunks.findall(text))), np.int32)

    def decode(self, ids: list[int]) -> str:
        text = b"".join(map(self.outputs.__getitem__, ids)).decode("utf-8", "replace")
        return text[1:] if self.prefix and text.startswith(" ") else text


def _encode(model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        transducer = Transducer.compile(model.value)
        for whole in batches:
            for batch in text_chunks(whole):
                texts = batch.column("text").to_pylist()
                ids = [transducer.encode(t) if t else np.empty(0, np.int32) for t in texts]
                same = [transducer.decode(i.tolist()) == (t or "") for i, t in zip(ids, texts)]
                ends = np.concatenate([[0], np.cumsum([len(i) for i in ids])]).astype(np.int32)
                flat = pa.array(np.concatenate(ids) if ids else np.empty(0, np.int32))
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(np.diff(ends).astype(np.int64)), pa.ListArray.from_arrays(pa.array(ends), flat), pa.array(same, pa.bool_())], ["doc_id", "n_tokens", "ids", "round_trip"])

    return run


def _decode(model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        transducer = Transducer.compile(model.value)
        for batch in batches:
            texts = [transducer.decode(i or []) for i in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(texts, pa.string())], ["doc_id", "text"])

    return run


def encode_pieces(docs: DataFrame, model: bytes | None = None) -> DataFrame:
    """(doc_id, n_tokens, ids, round_trip) of every whole text.

    round_trip says whether the ids decode to the text again; a text that holds
    the space mark itself does not. Null and empty texts have no ids. The model
    (a few hundred kB) is broadcast. Other columns are ignored.
    """
    model = docs.sparkSession.sparkContext.broadcast(model or default_model())
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(_encode(model), "doc_id long, n_tokens long, ids array<int>, round_trip boolean")


def decode_pieces(encoded: DataFrame, model: bytes | None = None) -> DataFrame:
    """(doc_id, text) of (doc_id, ids) rows; null and empty lists give an empty text."""
    model = encoded.sparkSession.sparkContext.broadcast(model or default_model())
    return encoded.select("doc_id", "ids").mapInArrow(_decode(model), "doc_id long, text string")


def op6_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_pieces(table(spark, sf_dir, "documents"))
