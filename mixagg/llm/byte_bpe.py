"""Byte-level BPE through a sentencepiece model that is written straight from a rank file.

Every byte maps to one printable character; each vocabulary entry becomes a piece of such characters scored by its
negative rank, with identity normalisation, so the library's merges follow the ranks.  Pre-tokens are encoded
separately (a pre-token that is itself an entry is that entry) and decoded by the inverse mapping.
Defined cases: null or empty texts have no tokens; texts of any length are encoded whole; repeated rows are rows of
their own; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import base64
import hashlib
import json
import struct
from functools import lru_cache

import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixagg.llm.pretokens import PretokenCache, Pretokens
from mixagg.llm.textkit import over_texts


@lru_cache(maxsize=4)
def read_ranks(path: str) -> dict[bytes, int]:
    """Ranks by byte string, from a rank file or from a byte-level BPE's JSON, whose ids follow its merges."""
    if path.endswith(".json"):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        special = {t["content"] for t in spec.get("added_tokens", [])}
        back = {c: b for b, c in enumerate(byte_alphabet())}
        return {bytes(back[c] for c in piece): i for piece, i in spec["model"]["vocab"].items() if piece not in special}
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


def byte_alphabet() -> list[str]:
    """A visible character for each byte: itself where it is printable Latin-1, else one from U+0100 on."""
    out, extra = [], 0
    for b in range(256):
        if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255:
            out.append(chr(b))
        else:
            out.append(chr(256 + extra))
            extra += 1
    return out


_ALPHABET = byte_alphabet()
_TO_PIECE = dict(enumerate(_ALPHABET))


def to_piece(raw: bytes) -> str:
    return raw.decode("latin-1").translate(_TO_PIECE)


def _varint(n: int) -> bytes:
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def _field(number: int, value: bytes | str | int | float) -> bytes:
    """One protobuf field: length-delimited, varint or 32-bit float."""
    if isinstance(value, float):
        return _varint(number << 3 | 5) + struct.pack("<f", value)
    if isinstance(value, int):
        return _varint(number << 3) + _varint(value)
    raw = value.encode() if isinstance(value, str) else value
    return _varint(number << 3 | 2) + _varint(len(raw)) + raw


def serialise_model(ranks: dict[bytes, int]) -> bytes:
    """The serialised model: ids are the ranks; one unknown piece stands after the last."""
    pieces = [b""] * (max(ranks.values()) + 1)
    for raw, rank in ranks.items():
        pieces[rank] = _field(1, to_piece(raw)) + _field(2, float(-rank)) + _field(3, 1)
    for i, p in enumerate(pieces):
        if not p:  # a free rank
            pieces[i] = _field(1, f"⁇{i}") + _field(2, -1e9) + _field(3, 5)
    pieces.append(_field(1, "⁇unk") + _field(2, 0.0) + _field(3, 2))
    trainer = _field(3, 2) + _field(4, len(pieces)) + _field(40, len(pieces) - 1)
    normaliser = _field(1, "identity") + _field(3, 0) + _field(4, 0) + _field(5, 0)
    return b"".join(_field(1, p) for p in pieces) + _field(2, trainer) + _field(3, normaliser)


class ByteBpe:
    """Encodes pre-tokens and decodes ids."""

    def __init__(self, path: str) -> None:
        self.ranks = read_ranks(path)
        self.raw = {i: b for b, i in self.ranks.items()}
        self.model = sentencepiece.SentencePieceProcessor(model_proto=serialise_model(self.ranks))

    def encode_many(self, tokens: list[str]) -> list[list[int]]:
        raw = [t.encode() for t in tokens]
        out = [[r] if (r := self.ranks.get(b)) is not None else None for b in raw]
        rest = [i for i, x in enumerate(out) if x is None]
        for i, ids in zip(rest, self.model.encode([to_piece(raw[i]) for i in rest], out_type=int, num_threads=1) if rest else []):
            out[i] = ids
        return out

    def decode(self, ids: list[int]) -> bytes:
        return b"".join([self.raw[i] for i in ids])


@lru_cache(maxsize=2)
def codec(path: str) -> tuple[ByteBpe, PretokenCache]:
    """One codec and one cache per worker; entries are the ids' decimal text and the decoded bytes."""
    bpe = ByteBpe(path)
    return bpe, PretokenCache(lambda tokens: [(b",".join([b"%d" % i for i in ids]), bpe.decode(ids)) for ids in bpe.encode_many(tokens)])


def encode_digests(docs: DataFrame, path: str, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """Per document the number of ids, and digests of the ids and of the decoded bytes."""

    def run(part, texts):
        _, cache = codec(path)
        tokens = Pretokens(texts)
        at = cache.lookup(tokens).tolist()
        entries, n, ids_sha, text_sha = cache.entries, [], [], []
        for a, b in zip(tokens.first[:-1].tolist(), tokens.first[1:].tolist()):
            mine = [entries[i] for i in at[a:b]]
            ids = b",".join([x[0] for x in mine])
            n.append(ids.count(b",") + 1 if mine else 0)
            ids_sha.append(hashlib.sha256(ids).hexdigest())
            text_sha.append(hashlib.sha256(b"".join([x[1] for x in mine])).hexdigest())
        return pa.record_batch([part.column(0), pa.array(n, pa.int64()), pa.array(ids_sha), pa.array(text_sha)], ["id", "n_tokens", "ids_sha256", "decoded_sha256"])

    kind = docs.schema[id_col].dataType.simpleString()
    out = docs.select(F.col(id_col).alias("id"), F.col(text).alias("text")).mapInArrow(over_texts(run), f"id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")
    return out.withColumnRenamed("id", id_col)


def encode_ids(docs: DataFrame, path: str, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """The general form: each document's ids as an array."""

    def run(part, texts):
        _, cache = codec(path)
        tokens = Pretokens(texts)
        at = cache.lookup(tokens).tolist()
        rows = [[int(x) for i in at[a:b] for x in cache.entries[i][0].split(b",")] for a, b in zip(tokens.first[:-1].tolist(), tokens.first[1:].tolist())]
        return pa.record_batch([part.column(0), pa.array(rows, pa.list_(pa.int32()))], ["id", "ids"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("id"), F.col(text).alias("text")).mapInArrow(over_texts(run), f"id {kind}, ids array<int>").withColumnRenamed("id", id_col)


def decode_ids(rows: DataFrame, path: str, ids: str = "ids", out: str = "text") -> DataFrame:
    """``rows`` with a binary column of the decoded bytes, by the inverse mapping."""
    names = rows.columns
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema) + f", `{out}` binary"

    def run(batches):
        bpe, _ = codec(path)
        for batch in batches:
            values = batch.column(names.index(ids)).to_pylist()
            yield pa.record_batch([*batch.columns, pa.array([bpe.decode(v or []) for v in values], pa.binary())], [*names, out])

    return rows.mapInArrow(run, schema)
