"""Byte-level BPE through a sentencepiece model that is written straight from a rank file.

Each byte stands for one printable character, a piece is the characters of a token's bytes, and its score is the
negative rank: sentencepiece then merges the pair of lowest rank first, leftmost among equals, as rank-based encoders do.
Normalisation is the identity.  Pre-tokens are encoded one by one, each distinct one once a worker; decoding inverts the
mapping.  Null and empty texts give no ids; repeated rows are encoded alike; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import hashlib
import struct

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from . import storage
from .textkit import BoundedCache, encoded, lean, slices, word_chunks, worker_cache

ENCODED = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def byte_characters() -> list[str]:
    """A printable character for each byte: itself where Latin-1 prints it, else the next code point from 256 on."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    out, spare = [], 256
    for b in range(256):
        out.append(chr(b if b in plain else spare))
        spare += b not in plain
    return out


def read_ranks(blob: bytes) -> dict[bytes, int]:
    return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in blob.splitlines() if line)}


def _varint(n: int) -> bytes:
    out = b""
    while n > 127:
        out, n = out + bytes([n & 127 | 128]), n >> 7
    return out + bytes([n])


def _message(field: int, body: bytes) -> bytes:
    return _varint(field << 3 | 2) + _varint(len(body)) + body


def _number(field: int, n: int) -> bytes:
    return _varint(field << 3) + _varint(n)


def sentencepiece_model(ranks: dict[bytes, int]) -> bytes:
    """A serialised ModelProto: the unknown piece as id 0, then a piece for each rank; so a piece's id is its rank's place plus 1."""
    characters = byte_characters()
    pieces = [_message(1, _message(1, b"<unk>") + struct.pack("<Bf", 2 << 3 | 5, 0.0) + _number(3, 2))]
    for token, rank in sorted(ranks.items(), key=lambda x: x[1]):
        text = "".join(characters[b] for b in token).encode()
        pieces.append(_message(1, _message(1, text) + struct.pack("<Bf", 2 << 3 | 5, -float(rank)) + _number(3, 1)))
    trainer = _number(3, 2) + _number(4, len(ranks) + 1) + _number(35, 0) + _number(24, 0) + _number(40, 0)
    trainer += _number(41, (1 << 64) - 1) + _number(42, (1 << 64) - 1) + _number(43, (1 << 64) - 1)
    normalizer = _message(1, b"identity") + _number(3, 0) + _number(4, 0) + _number(5, 0)
    return b"".join(pieces) + _message(2, trainer) + _message(3, normalizer)


class BytePairCodec:
    """Encode texts to ids and ids to bytes."""

    def __init__(self, rank_file: bytes, pattern: str):
        import sentencepiece

        self.ranks = read_ranks(rank_file)
        self.by_place = np.array(sorted(self.ranks.values()), dtype="<u4")
        self.bytes_of = {rank: token for token, rank in self.ranks.items()}
        self.model = sentencepiece.SentencePieceProcessor(model_proto=sentencepiece_model(self.ranks))
        self.pattern = regex.compile(pattern)
        self.table = dict(enumerate(byte_characters()))
        self.known, self.chunks = BoundedCache(48 << 20), BoundedCache(80 << 20)

    def _ids(self, pieces: list[str]) -> dict[str, bytes]:
        """Ids of pre-tokens that are not kept."""
        out, rest = {}, []
        for p in pieces:
            rank = self.ranks.get(encoded(p))
            if rank is None:
                rest.append(p)
            else:
                out[p] = struct.pack("<I", rank)
        mapped = [encoded(p).decode("latin-1").translate(self.table) for p in rest]
        for p, ids in zip(rest, self.model.encode(mapped, num_threads=1) if mapped else [], strict=True):
            out[p] = self.by_place[np.array(ids) - 1].tobytes()
        return out

    def encode(self, texts: list[str]) -> list[bytes]:
        """Ids of each text, four little-endian bytes an id.

        What stands between two single blanks, each between two characters that are no white space, is split and encoded
        once: the pattern starts a match at such a blank, whatever surrounds it.  Long chunks and pre-tokens are not kept.
        """
        known, chunks = self.known, self.chunks
        cut = [word_chunks(t) if t else [] for t in texts]
        new = {c: self.pattern.findall(c) for c in {c for cs in cut for c in cs} - chunks.keys()}
        got = self._ids(list({p for ps in new.values() for p in ps} - known.keys()))
        known.keep(got.items())
        long = {p for p in got if len(p) > known.LONGEST}
        fresh = {}
        for c, ps in new.items():
            fresh[c] = b"".join([got[p] if p in got else known[p] for p in ps] if long else map(known.__getitem__, ps))
        chunks.keep(fresh.items())
        long = {c for c in fresh if len(c) > chunks.LONGEST}
        out = [b"".join(map(chunks.__getitem__, cs) if not long or long.isdisjoint(cs) else [fresh[c] if c in fresh else chunks[c] for c in cs]) for cs in cut]
        known.tidy()
        chunks.tidy()
        return out

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, np.frombuffer(ids, dtype="<u4").tolist()))


def encode_documents(docs: DataFrame, rank_file: bytes, pattern: str) -> DataFrame:
    """doc_id, the number of ids, and digests of the ids and of the text decoded from them; nothing is shuffled."""

    @lean
    def run(batches):
        cache = worker_cache("codec")
        if "codec" not in cache:
            cache["codec"] = BytePairCodec(rank_file, pattern)
        codec = cache["codec"]
        for ids, texts in slices(batches, ["doc_id", "text"]):
            codes = codec.encode([t or "" for t in texts])
            sha = [hashlib.sha256(c).hexdigest() for c in codes]
            back = [hashlib.sha256(codec.decode(c)).hexdigest() for c in codes]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array([len(c) // 4 for c in codes], pa.int64()), pa.array(sha), pa.array(back)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select("doc_id", "text").mapInArrow(run, ENCODED)


def op3_bytebpe(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    with open(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), "rb") as f:
        ranks = f.read()
    return encode_documents(storage.table(spark, sf_dir, "documents"), ranks, public_tokenizers.PATTERN)
