"""Byte-level BPE by a sentencepiece model that is serialised from a rank vocabulary.

Each vocabulary entry becomes a piece whose bytes are mapped to printable
characters, scored by its negative rank, so that sentencepiece merges in rank
order; normalisation is the identity, and ids equal ranks. Texts are split by
the pre-token pattern, each pre-token is encoded on its own, and decoding maps
pieces back to bytes. Nothing is trained.
"""

from __future__ import annotations

import base64
import hashlib
import struct

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from callweave.tables import spread

UNKNOWN_PIECE = "\u2047"  # outside the alphabet of byte characters, so no text can spell it


def byte_alphabet() -> list[str]:
    """The printable character that stands for each byte: printable Latin-1 for itself, others from U+0100 on."""
    keeps = {b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255}
    spare = iter(range(256, 512))
    return [chr(b) if b in keeps else chr(next(spare)) for b in range(256)]


def read_ranks(path: str) -> dict[bytes, int]:
    """Vocabulary of a rank file: base64 of the bytes, a blank, the rank."""
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


def _varint(n: int) -> bytes:
    out = bytearray()
    while True:
        n, low = n >> 7, n & 127
        out.append(low | (128 if n else 0))
        if not n:
            return bytes(out)


def _field(number: int, value: bytes | int | float) -> bytes:
    """One protobuf field: length-delimited bytes, a float, or a varint."""
    if isinstance(value, bytes):
        return _varint(number << 3 | 2) + _varint(len(value)) + value
    if isinstance(value, float):
        return _varint(number << 3 | 5) + struct.pack("<f", value)
    return _varint(number << 3) + _varint(value)


def serialise_model(ranks: dict[bytes, int]) -> bytes:
    """A sentencepiece model file for `ranks`, whose ranks must be 0..n-1; the unknown piece gets id n."""
    pieces = sorted(ranks, key=ranks.__getitem__)
    if [ranks[p] for p in pieces] != list(range(len(pieces))):
        raise ValueError("ranks must run from 0 without gaps")
    if any(bytes([b]) not in ranks for b in range(256)):
        raise ValueError("the vocabulary must hold every single byte")
    char = byte_alphabet()
    # Field numbers and enums of the public sentencepiece_model.proto.
    normal, unknown, bpe = 1, 2, 2
    out = bytearray()
    for rank, piece in enumerate(pieces):
        text = "".join(char[b] for b in piece).encode("utf-8")
        out += _field(1, _field(1, text) + _field(2, float(-rank)) + _field(3, normal))
    out += _field(1, _field(1, UNKNOWN_PIECE.encode()) + _field(2, 0.0) + _field(3, unknown))
    out += _field(2, _field(3, bpe) + _field(4, len(pieces) + 1) + _field(40, len(pieces)))
    out += _field(3, _field(1, b"identity") + _field(3, 0) + _field(4, 0) + _field(5, 0))
    return bytes(out)


class Codec:
    """Encoder and decoder of one worker. Remembers the ids of pre-tokens, and forgets all of them beyond `memory` entries."""

    def __init__(self, model: bytes, pieces: list[bytes], pattern: str, memory: int = 200_000):
        import sentencepiece

        self.sp = sentencepiece.SentencePieceProcessor()
        self.sp.LoadFromSerializedProto(model)
        self.pieces, self.split, self.memory = pieces, regex.compile(pattern).findall, memory
        self.decimal = [str(i) for i in range(len(pieces))]
        self.alphabet = byte_alphabet()
        self.ranks = {p: i for i, p in enumerate(pieces)}
        self.known: dict[str, bytes] = {}

    def _learn(self, tokens: set[str]) -> None:
        """Pre-tokens that are whole pieces get their rank; the others go to sentencepiece, many in a call.

        The unknown piece stands between them: nothing merges with it, so each
        is encoded on its own, and its id marks their ends.
        """
        parts, size = [], 0
        for t in tokens:
            rank = self.ranks.get(t.encode("utf-8"))
            if rank is not None:
                self.known[t] = struct.pack("<i", rank)
                continue
            parts.append(t)
            size += len(t)
            if size > 4000:
                self._merge(parts)
                parts, size = [], 0
        if parts:
            self._merge(parts)

    def _merge(self, parts: list[str]) -> None:
        line = UNKNOWN_PIECE.join([self._mapped(t) for t in parts]) + UNKNOWN_PIECE
        ids = np.array(self.sp.encode(line, out_type=int), "<i4")
        raw, start = ids.tobytes(), 0
        ends = np.flatnonzero(ids == len(self.pieces)).tolist()
        if len(ends) != len(parts):
            raise ValueError("a pre-token holds what the byte alphabet lacks")
        for t, end in zip(parts, ends):
            self.known[t] = raw[4 * start : 4 * end]
            start = end + 1

    def _mapped(self, token: str) -> str:
        if token.isascii() and token[1:].isalnum() and (token[0] == " " or token[0].isalnum()):
            return token.replace(" ", self.alphabet[32])  # letters and digits stand for themselves
        return "".join([self.alphabet[b] for b in token.encode("utf-8")])

    def encode(self, text: str) -> tuple[np.ndarray, str]:
        """Ids of a text, and the same in decimals joined by blanks."""
        tokens = self.split(text)
        new = set(tokens).difference(self.known)
        if new:
            if len(self.known) + len(new) > self.memory:
                self.known.clear()
                new = set(tokens)
            self._learn(new)
        ids = np.frombuffer(b"".join(map(self.known.__getitem__, tokens)), "<i4")
        return ids, " ".join(map(self.decimal.__getitem__, ids.tolist()))

    def decode(self, ids: np.ndarray) -> bytes:
        return b"".join(map(self.pieces.__getitem__, ids.tolist()))


def encode_texts(
    docs: DataFrame,
    vocabulary: str,
    pattern: str,
    id_col: str = "doc_id",
    text_col: str = "text",
    keep_ids: bool = True,
) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 and, if `keep_ids`, ids (array) of every whole text.

    `vocabulary` is a rank file on the driver; what is broadcast is the model
    made of it, of the vocabulary's size whatever the corpus. Null and empty
    texts have no ids; null ids stay null; repeated rows stay repeated; other
    columns are ignored; an empty table gives an empty table. No shuffle.
    """
    ranks = read_ranks(vocabulary)
    spark = docs.sparkSession
    model = spark.sparkContext.broadcast(serialise_model(ranks))
    pieces = spark.sparkContext.broadcast(sorted(ranks, key=ranks.__getitem__))
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * keep_ids

    def run(batches):
        codec = Codec(model.value, pieces.value, pattern)
        sha = lambda b: hashlib.sha256(b).hexdigest()
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                rows = []
                for text in part.column(1):
                    ids, line = codec.encode(text.as_py() or "")
                    rows.append((len(ids), sha(line.encode()), sha(codec.decode(ids)), ids if keep_ids else None))
                n, a, b, kept = zip(*rows)
                cols = [part.column(0), pa.array(n, pa.int64()), pa.array(a), pa.array(b)]
                if keep_ids:
                    cols.append(pa.array(kept, pa.list_(pa.int32())))
                yield pa.RecordBatch.from_arrays(cols, [c.split()[0] for c in schema.split(", ")])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return spread(rows, "doc_id").mapInArrow(run, schema)


def decode_ids(encoded: DataFrame, vocabulary: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(doc_id, data binary): the bytes of each row's ids. Null ids give empty bytes; an id outside the vocabulary fails."""
    ranks = read_ranks(vocabulary)
    pieces = encoded.sparkSession.sparkContext.broadcast(sorted(ranks, key=ranks.__getitem__))

    def run(batches):
        for batch in batches:
            data = [b"".join([pieces.value[i] for i in ids.as_py() or []]) for ids in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(data, pa.binary())], ["doc_id", "data"])

    return encoded.select(F.col(id_col).cast("long").alias("doc_id"), F.col(ids_col).alias("ids")).mapInArrow(run, "doc_id long, data binary")
