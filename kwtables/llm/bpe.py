"""Byte-level BPE with forced boundaries: encoding, decoding and their digests.

A pair of bytes that is adjacent in no vocabulary token can never end up inside one token, so every
place where such a pair occurs is a certain cut. A pre-token is cut there, each fragment is merged on
its own, and the ids are concatenated (and remembered in a bounded table, as pre-tokens repeat).
Cuts are looked for inside pre-tokens only: the pre-tokeniser looks at neighbouring characters, so a cut
made before it could change how white space is grouped. The library's merge model encodes a fragment; splitting, special
tokens, concatenation and decoding are done here.

Defined results: null text counts as empty; empty text has no ids; strings of special tokens inside a text
become that token, as the library does by default; repeated rows give repeated results; columns of the input
other than the id and text columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
import os
import re
import struct
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship, trim

#: Entries kept in a worker's memo before it is emptied.
MEMO_ENTRIES = 100_000
#: Pre-tokens up to this many characters are remembered.
LONGEST_KEPT = 64


def byte_alphabet() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    own, shift = set(plain), 0
    out = []
    for b in range(256):
        if b in own:
            out.append(chr(b))
        else:
            out.append(chr(256 + shift))
            shift += 1
    return out


#: Below this code point Unicode's categories are long settled, so Python's ``re`` splits as the library does.
SETTLED = 0x250


def settled_splitter() -> re.Pattern:
    """The byte-level pre-tokeniser's pattern for texts below SETTLED, with its classes spelled out."""
    kinds: dict[str, list[str]] = {"L": [], "N": [], "blank": []}
    for c in map(chr, range(SETTLED)):
        kind = "blank" if c in "\t\n\x0b\x0c\r \x85\xa0" else unicodedata.category(c)[0]
        if kind in kinds:
            kinds[kind].append(re.escape(c))
    letters, digits, blanks = ("".join(k) for k in kinds.values())
    parts = ("'(?:[stmd]|re|ve|ll)", f" ?[{letters}]+", f" ?[{digits}]+", f" ?[^{letters}{digits}{blanks}]+", f"[{blanks}]+(?![^{blanks}])", f"[{blanks}]+")
    return re.compile("|".join(parts))


class ByteBpe:
    """Merges of one tokeniser file (``tokenizers`` JSON with a byte-level BPE model)."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        if model["type"] != "BPE" or spec["normalizer"] or (spec["pre_tokenizer"] or {}).get("type") != "ByteLevel":
            raise ValueError("a byte-level BPE file without normaliser is needed")
        added = [t for t in spec["added_tokens"] if t["content"]]
        if any(t["single_word"] or t["lstrip"] or t["rstrip"] for t in added):
            raise ValueError("added tokens that match with their surroundings are not supported")
        library = Tokenizer.from_file(path)
        self.library_split = library.pre_tokenizer.pre_tokenize_str
        #: The merge model alone, without pre-tokenising: applied to one fragment at a time.
        self.merge = library.model.tokenize
        library.no_truncation()
        library.no_padding()
        self.library = library
        self.settled = settled_splitter().findall
        self.unsettled = re.compile(f"[^\0-{chr(SETTLED - 1)}]").search
        self.mapped = byte_alphabet()
        self.unmapped = {c: b for b, c in enumerate(self.mapped)}
        self.vocab: dict[str, int] = model["vocab"]
        self.special = {t["content"]: t["id"] for t in added}
        longest_first = sorted(self.special, key=len, reverse=True)
        self.special_re = re.compile("|".join(map(re.escape, longest_first))) if added else None
        self.token_bytes: dict[int, bytes] = {i: bytes(self.unmapped[c] for c in t) for t, i in self.vocab.items()}
        self.token_bytes |= {i: t.encode() for t, i in self.special.items()}
        self.inner: set[tuple[str, str]] = {pair for t in self.vocab for pair in zip(t, t[1:], strict=False)}
        self.packed: dict[str, bytes] = {}  # pre-token -> ids as little-endian 32-bit

    def split(self, text: str) -> list[str]:
        """Pre-tokens of an ordinary stretch of text, as substrings."""
        if not self.unsettled(text):
            return self.settled(text)
        return [text[a:b] for _, (a, b) in self.library_split(text)]

    def fragments(self, piece: str) -> list[str]:
        """``piece`` (one character for each byte) cut wherever two bytes are adjacent in no vocabulary token."""
        inner = self.inner
        cuts = [i for i, pair in enumerate(zip(piece, piece[1:], strict=False), 1) if pair not in inner]
        return [piece[a:b] for a, b in zip([0, *cuts], [*cuts, len(piece)], strict=True)] if cuts else [piece]

    def pack_piece(self, piece: str) -> bytes:
        """Ids of one pre-token: those of its fragments, one after the other."""
        mapped = "".join([self.mapped[b] for b in piece.encode()])
        ids = [t.id for f in self.fragments(mapped) for t in self.merge(f)]
        return struct.pack(f"<{len(ids)}I", *ids)

    def piece_counts(self, pieces: list[str]) -> list[int]:
        """Number of ids of each pre-token, in bulk; a pre-token on its own is split no further."""
        return [len(e) for e in self.library.encode_batch_fast(pieces, add_special_tokens=False)]

    def sections(self, text: str) -> Iterator[tuple[str, int | None]]:
        """Ordinary stretches (id None) and special tokens of ``text`` in order."""
        if not self.special_re or not self.special_re.search(text):
            yield text, None
            return
        at = 0
        for m in self.special_re.finditer(text):
            if m.start() > at:
                yield text[at : m.start()], None
            yield m[0], self.special[m[0]]
            at = m.end()
        if at < len(text):
            yield text[at:], None

    def pack(self, text: str) -> bytes:
        """Ids of a whole text as little-endian unsigned 32-bit integers."""
        out: list[bytes] = []
        packed = self.packed
        for part, special in self.sections(text):
            if special is not None:
                out.append(struct.pack("<I", special))
                continue
            for piece in self.split(part):
                ids = packed.get(piece)
                if ids is None:
                    if len(packed) >= MEMO_ENTRIES:
                        packed.clear()
                    ids = self.pack_piece(piece)
                    if len(piece) <= LONGEST_KEPT:
                        packed[piece] = ids
                out.append(ids)
        return b"".join(out)

    def encode(self, text: str) -> list[int]:
        return np.frombuffer(self.pack(text), dtype="<u4").tolist()

    def decode_bytes(self, packed: bytes) -> bytes:
        return b"".join(map(self.token_bytes.__getitem__, np.frombuffer(packed, dtype="<u4").tolist()))

    def decode(self, ids: list[int]) -> str:
        return b"".join(map(self.token_bytes.__getitem__, ids)).decode("utf-8", "replace")


_loaded: dict[str, ByteBpe] = {}


def load(path: str) -> ByteBpe:
    """One tokeniser for each worker process and path."""
    if path not in _loaded:
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a task has one core
        _loaded[path] = ByteBpe(path)
    return _loaded[path]


def encode_documents(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col, ids array<int>, decoded string`` for each row; ``path`` must name the tokeniser file on every worker."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path)
        for batch in batches:
            packs = [bpe.pack(t or "") for t in batch.column(1).to_pylist()]
            lists = pa.array([np.frombuffer(p, dtype="<u4").astype(np.int32) for p in packs], pa.list_(pa.int32()))
            texts = pa.array([bpe.decode_bytes(p).decode("utf-8", "replace") for p in packs], pa.string())
            yield pa.RecordBatch.from_arrays([batch.column(0), lists, texts], names=[id_col, "ids", "decoded"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, ids array<int>, decoded string")


def encode_digests(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col, n_tokens, ids_sha256, decoded_sha256`` for each row: encoded, decoded from the ids, and digested in one pass."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path)
        for batch in batches:
            counts, ids, texts = [], [], []
            for t in batch.column(1):
                p = bpe.pack(t.as_py() or "")
                counts.append(len(p) // 4)
                ids.append(hashlib.sha256(p).hexdigest())
                texts.append(hashlib.sha256(bpe.decode_bytes(p).decode("utf-8", "replace").encode()).hexdigest())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(counts, pa.int64()), pa.array(ids, pa.string()), pa.array(texts, pa.string())],
                names=[id_col, "n_tokens", "ids_sha256", "decoded_sha256"],
            )
        trim()

    kind = docs.schema[id_col].dataType.simpleString()
    out = f"`{id_col}` {kind}, n_tokens bigint, ids_sha256 string, decoded_sha256 string"
    return docs.select(id_col, text_col).mapInArrow(run, out)


def decode_ids(encoded: DataFrame, path: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """``id_col, decoded`` from stored id lists (null: null)."""
    ship(encoded.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path)
        for batch in batches:
            texts = [None if x is None else bpe.decode(x) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=[id_col, "decoded"])

    kind = encoded.schema[id_col].dataType.simpleString()
    return encoded.select(id_col, F.col(ids_col)).mapInArrow(run, f"`{id_col}` {kind}, decoded string")
