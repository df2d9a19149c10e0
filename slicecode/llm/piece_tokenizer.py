"""SentencePiece encoding and decoding on the ``tokenizers`` library.

The model's protobuf is parsed here (wire format only), and its parts are rebuilt: normaliser (prefix space, space
to the metaspace marker, precompiled character map, extra white space), unigram scores or the merges that BPE scores
imply, unknown piece and byte fallback. Batches are encoded by the library's threads.

Where no piece has the marker after another character, and where the model is BPE, no merge reaches over the border
before a run of markers; the text is then the sequence of its marker-led segments, and each distinct segment is encoded
once, decoded again, and held against the ``sentencepiece`` library. Otherwise whole texts are.
"""

from __future__ import annotations

import re
import struct
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from tokenizers import Regex, Tokenizer, decoders, models, normalizers

from slicecode.llm.common import slices_by_bytes

MODEL_FILE = "/opt/tokenizers/piece_bpe_32k.model"
MARK = "▁"
NORMAL, UNKNOWN, CONTROL, USER, BYTE, UNUSED = 1, 2, 3, 4, 6, 5
UNIGRAM, BPE = 1, 2
_SEGMENT = re.compile(f"{MARK}*[^{MARK}]+|{MARK}+")


def wire(raw: bytes) -> Iterator[tuple[int, int | bytes]]:
    """(field number, value) of a protobuf message: varints as integers, everything else as bytes."""

    def varint(at: int) -> tuple[int, int]:
        value = shift = 0
        while True:
            byte = raw[at]
            value, shift, at = value | (byte & 127) << shift, shift + 7, at + 1
            if byte < 128:
                return value, at

    at = 0
    while at < len(raw):
        key, at = varint(at)
        kind = key & 7
        if kind == 0:
            value, at = varint(at)
        elif kind in (1, 5):
            size = 8 if kind == 1 else 4
            value, at = raw[at : at + size], at + size
        elif kind == 2:
            size, at = varint(at)
            value, at = raw[at : at + size], at + size
        else:
            raise ValueError(f"wire type {kind}")
        yield key >> 3, value


@dataclass
class PieceModel:
    pieces: list[tuple[str, float, int]] = field(default_factory=list)
    kind: int = UNIGRAM
    byte_fallback: bool = False
    unknown: int = 0
    charsmap: bytes = b""
    dummy_prefix: bool = True
    squeeze: bool = True
    escape: bool = True

    @classmethod
    def parse(cls, raw: bytes) -> PieceModel:
        out = cls()
        for number, value in wire(raw):
            if number == 1:
                f = dict(wire(value))
                out.pieces.append((f.get(1, b"").decode(), struct.unpack("<f", f[2])[0] if 2 in f else 0.0, f.get(3, NORMAL)))
            elif number == 2:
                f = dict(wire(value))
                out.kind, out.byte_fallback, out.unknown = f.get(3, UNIGRAM), bool(f.get(35, 0)), f.get(40, 0)
            elif number == 3:
                f = dict(wire(value))
                out.charsmap, out.dummy_prefix, out.squeeze, out.escape = f.get(2, b""), bool(f.get(3, 1)), bool(f.get(4, 1)), bool(f.get(5, 1))
        return out

    @property
    def by_segment(self) -> bool:
        return self.kind == BPE and self.escape and not self.charsmap and not self.squeeze and not any(MARK in p.lstrip(MARK) for p, _, _ in self.pieces)

    def merges(self) -> list[tuple[str, str]]:
        """Every split of a piece in two pieces, by the piece's score (high first), then by the parts' ids.

        Runs of one character may share one score (the runs of spaces); the reference then takes the longest run that is a
        piece, again and again. Ranked by length, long runs first, the merges do the same.
        """
        ids = {p: i for i, (p, _, kind) in enumerate(self.pieces) if kind in (NORMAL, USER)}
        shared = Counter(s for _, s, kind in self.pieces if kind == NORMAL)
        found = []
        for p, s, kind in self.pieces:
            if kind == NORMAL and len(p) > 1:
                run = shared[s] > 1 and len(set(p)) == 1
                found += [(-s, -len(p) if run else 0, ids[p[:c]], ids[p[c:]], p[:c], p[c:]) for c in range(1, len(p)) if p[:c] in ids and p[c:] in ids]
        return [(a, b) for *_, a, b in sorted(found)]

    def tokenizer(self) -> Tokenizer:
        if self.kind == UNIGRAM:
            model = models.Unigram([(p, s) for p, s, _ in self.pieces], unk_id=self.unknown, byte_fallback=self.byte_fallback)
        elif self.kind == BPE:
            model = models.BPE({p: i for i, (p, _, _) in enumerate(self.pieces)}, self.merges(), unk_token=self.pieces[self.unknown][0], fuse_unk=True, byte_fallback=self.byte_fallback)
        else:
            raise ValueError(f"model type {self.kind} is neither unigram nor BPE")
        made = Tokenizer(model)
        steps = [normalizers.Precompiled(self.charsmap)] if self.charsmap else []
        if self.squeeze:
            steps += [normalizers.Strip(), normalizers.Replace(Regex(" {2,}"), " ")]
        if self.dummy_prefix:
            steps.append(normalizers.Prepend(MARK if self.escape else " "))
        if self.escape:
            steps.append(normalizers.Replace(" ", MARK))
        made.normalizer = normalizers.Sequence(steps)
        ends = [decoders.Replace(MARK, " ")] * self.escape + [decoders.ByteFallback()] * self.byte_fallback + [decoders.Fuse()] + [decoders.Strip(" ", 1, 0)] * self.dummy_prefix
        made.decoder = decoders.Sequence(ends)
        return made


class Codec:
    """Encoder and decoder of one worker process.

    ``most`` bounds the remembered segments: a full generation becomes the old one, and the old one is dropped.
    """

    def __init__(self, raw: bytes, most: int = 150_000) -> None:
        self.model = PieceModel.parse(raw)
        self.tok = self.model.tokenizer()
        self.plain = Tokenizer.from_str(self.tok.to_str())  # takes text that is normalised already
        self.plain.normalizer = normalizers.Sequence([])
        self.tok.encode_special_tokens = self.plain.encode_special_tokens = True
        self.reference = sentencepiece.SentencePieceProcessor(model_proto=raw)
        self.by_segment, self.most = self.model.by_segment and self.model.dummy_prefix, most
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        self.faulty: dict[str, tuple[bool, bool]] = {}  # segments that fail parity or the round trip
        names = [p for p, _, _ in self.model.pieces]
        self.leads = np.array([p.startswith(MARK) for p in names])
        self.spelled = [bytes([int(p[3:5], 16)]) if kind == BYTE else p.replace(MARK, " ").encode() for p, _, kind in self.model.pieces]

    def _checked(self, texts: list[str]) -> list[tuple[bytes, bool, bool]]:
        """(ids, same as the reference's, decodes to the text) of each whole text."""
        ids = [e.ids if t else [] for t, e in zip(texts, self.tok.encode_batch_fast(texts, add_special_tokens=False), strict=True)]
        same, back = self.reference.encode(texts, num_threads=1), self.decode(ids)
        return [(np.array(a, "<i4").tobytes(), a == b, c == t) for t, a, b, c in zip(texts, ids, same, back, strict=True)]

    def _learn(self, segments: list[str], block: int = 200) -> None:
        """Encode new segments. Those with the one marker in front are joined in blocks: a piece with a marker begins
        the next segment. The others, and blocks that fail a check, are taken one by one."""
        alone = [s for s in segments if s[0] != MARK or MARK in s[1:] or len(s) == 1]
        lead = [s for s in segments if s[0] == MARK and len(s) > 1 and MARK not in s[1:]]
        blocks = [lead[at : at + block] for at in range(0, len(lead), block)]
        encoded = self.plain.encode_batch_fast(["".join(b) for b in blocks], add_special_tokens=False)
        texts = ["".join(b).replace(MARK, " ") for b in blocks]
        same = self.reference.encode([t[1:] for t in texts], num_threads=1)  # the prefix comes back with the normaliser
        for part, e, text, ref in zip(blocks, encoded, texts, same, strict=True):
            ids = np.array(e.ids, "<i4")
            cuts = np.flatnonzero(self.leads[ids])
            if len(cuts) == len(part) and e.ids == ref and b"".join([self.spelled[i] for i in e.ids]) == text.encode("utf-8", "replace"):
                raw, ends = ids.tobytes(), np.append(cuts[1:], len(ids)).tolist()
                self.young.update(zip(part, [raw[4 * x : 4 * y] for x, y in zip(cuts.tolist(), ends, strict=True)], strict=True))
            else:
                alone += part
        if alone:
            ids = [e.ids for e in self.plain.encode_batch_fast(alone, add_special_tokens=False)]
            heads = [s[1:].replace(MARK, " ") if s[0] == MARK else s for s in alone]  # every text begins with a marker: it is the prefix
            for s, head, got, ref in zip(alone, heads, ids, self.reference.encode(heads, num_threads=1), strict=True):
                if s == MARK:
                    ref = [self.reference.piece_to_id(MARK)]  # a space before a run's end has no text of its own
                self.young[s] = np.array(got, "<i4").tobytes()
                back = b"".join([self.spelled[i] for i in got]) == s.replace(MARK, " ").encode("utf-8", "replace")
                if got != ref or not back:
                    self.faulty[s] = (got == ref, back)

    def encode(self, texts: list[str | None]) -> tuple[list[bytes], list[bool], list[bool]]:
        """For each text: its ids (int32, little endian), parity with the reference, exact round trip. Null counts as empty."""
        if not self.by_segment:
            found = self._checked([t or "" for t in texts])
            return [f[0] for f in found], [f[1] for f in found], [f[2] for f in found]
        cut = [_SEGMENT.findall(MARK + t.replace(" ", MARK)) if t else [] for t in texts]
        if len(self.young) > self.most:
            self.old, self.young, self.faulty = self.young, {}, {k: v for k, v in self.faulty.items() if k in self.young}
        wanted = set().union(*cut).difference(self.young)
        for s in wanted & self.old.keys():
            self.young[s] = self.old[s]
        self._learn(list(wanted.difference(self.young)))
        ids = [b"".join(map(self.young.__getitem__, c)) for c in cut]
        if not self.faulty:
            return ids, [True] * len(texts), [MARK not in (t or "") for t in texts]
        bad = [[self.faulty[s] for s in c if s in self.faulty] for c in cut]
        return ids, [all(x[0] for x in b) for b in bad], [all(x[1] for x in b) and MARK not in (t or "") for t, b in zip(texts, bad, strict=True)]

    def decode(self, ids: list[list[int]]) -> list[str]:
        return self.tok.decode_batch([list(map(int, i)) for i in ids], skip_special_tokens=False)


_CODECS: dict[int, Codec] = {}


def _codec(raw: bytes) -> Codec:
    """One codec for each model and worker process."""
    key = hash(raw)
    if key not in _CODECS:
        _CODECS.clear()
        _CODECS[key] = Codec(raw)
    return _CODECS[key]


def read_model(path: str = MODEL_FILE) -> bytes:
    """The model's bytes, read on the driver; they travel with the job."""
    with open(path, "rb") as f:
        return f.read()


def encode(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", model_file: str = MODEL_FILE) -> DataFrame:
    """One row for each input row: doc_id, n_tokens, ids (array of int), parity (same ids as the sentencepiece
    library), round_trip (decoding gives the text back).

    Null and empty texts have no ids. A text that itself has the marker character decodes with spaces in its place,
    so its round trip is false. Empty table: no rows.
    """
    sent = docs.sparkSession.sparkContext.broadcast(read_model(model_file))  # the vocabulary's size
    narrow = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).cast("string").alias("text"))
    schema = T.StructType([narrow.schema["doc_id"]] + list(T.StructType.fromDDL("n_tokens long, ids array<int>, parity boolean, round_trip boolean")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _codec(sent.value)
        for whole in batches:
            for batch in slices_by_bytes(whole, 1 << 20):
                raw, same, back = codec.encode(batch.column("text").to_pylist())
                sizes = np.fromiter((len(r) // 4 for r in raw), np.int64, len(raw))
                flat = np.frombuffer(b"".join(raw), "<i4")
                ids = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(sizes))), pa.int32()), pa.array(flat, pa.int32()))
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(sizes, pa.int64()), ids, pa.array(same, pa.bool_()), pa.array(back, pa.bool_())], names=schema.names)

    return narrow.mapInArrow(run, schema)


def decode(tokens: DataFrame, ids: str = "ids", model_file: str = MODEL_FILE) -> DataFrame:
    """``tokens`` with a column ``decoded``; null ids give a null text."""
    sent = tokens.sparkSession.sparkContext.broadcast(read_model(model_file))

    @F.pandas_udf("string")
    def text_of(values):
        out = iter(_codec(sent.value).decode([v for v in values if v is not None]))
        return values.map(lambda v: None if v is None else next(out))

    return tokens.withColumn("decoded", text_of(F.col(ids)))
