"""SentencePiece encoding that keeps byte offsets, and decoding.

The model file is read here for its normaliser: a compiled double-array trie of
source strings and their replacements. Normalising takes the longest prefix of the
rest of the text that the trie knows, else one character, and records for every
normalised byte the source byte it came from. A piece covers a range of normalised
bytes, so the record projects it to a range of source bytes. Merging of pieces is
the library's.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Characters of source text that a batch holds while it is encoded and sent back.
BATCH_CHARS = 2 << 20


def _fields(raw: bytes) -> Iterator[tuple[int, int | bytes]]:
    """Field numbers and values of a serialized protocol-buffer message."""
    at = 0

    def varint() -> int:
        nonlocal at
        value = shift = 0
        while True:
            byte = raw[at]
            at += 1
            value |= (byte & 0x7F) << shift
            shift += 7
            if byte < 0x80:
                return value

    while at < len(raw):
        key = varint()
        if key & 7 == 0:
            yield key >> 3, varint()
            continue
        size = {1: 8, 5: 4}.get(key & 7) or varint()
        yield key >> 3, raw[at : at + size]
        at += size


def tokenizer_path(name: str = "piece_bpe_32k.model") -> str:
    """Place of a public vocabulary file on this machine."""
    import public_tokenizers

    return public_tokenizers.path(name)


class CharMap:
    """Longest-prefix replacement through the compiled map of a model's normaliser."""

    def __init__(self, blob: bytes = b""):
        self.units: list[int] = []
        self.values = b""
        if blob:
            size = int.from_bytes(blob[:4], "little")
            self.units = np.frombuffer(blob[4 : 4 + size], "<u4").tolist()
            self.values = blob[4 + size :]

    def longest(self, src: bytes, at: int) -> tuple[int, bytes] | None:
        """Length of the longest known prefix of ``src[at:]`` and its replacement."""
        units, found = self.units, None
        if not units:
            return None
        offset = lambda u: (u >> 10) << ((u & 0x200) >> 6)
        node = offset(units[0])
        for i in range(at, len(src)):
            node ^= src[i]
            if node >= len(units):
                break
            unit = units[node]
            if unit & 0x800000FF != src[i]:
                break
            node ^= offset(unit)
            if unit & 0x100:
                found = i + 1 - at, units[node] & 0x7FFFFFFF
        if found is None:
            return None
        value = self.values[found[1] : self.values.index(b"\0", found[1])]
        return found[0], value

    def apply(self, src: bytes) -> tuple[bytes, np.ndarray]:
        """Normalised bytes, and for each of them (and the end) the source byte it starts from."""
        if not self.units:
            return src, np.arange(len(src) + 1, dtype=np.int64)
        out, origin, at = bytearray(), [], 0
        while at < len(src):
            if (hit := self.longest(src, at)) is None:
                lead = src[at]
                size = 1 if lead < 0x80 else 2 if lead < 0xE0 else 3 if lead < 0xF0 else 4
                size, value = size, src[at : at + size]
            else:
                size, value = hit
            out += value
            origin += [at] * len(value) if hit else range(at, at + len(value))
            at += size
        return bytes(out), np.array([*origin, len(src)], np.int64)


class Encoder:
    """One model, loaded from its bytes; safe to build on each worker."""

    def __init__(self, model: bytes):
        self.library = sentencepiece.SentencePieceProcessor(model_proto=model)
        spec, pieces = {}, []
        for field, value in _fields(model):
            if field == 1:
                pieces.append(dict(_fields(value)))
            elif field == 3:
                spec = dict(_fields(value))
        self.map = CharMap(spec.get(2, b""))
        if not spec.get(5, 1) or spec.get(4, 1):
            raise ValueError("models that keep plain blanks or drop extra ones are not supported")
        self.prefix = bool(spec.get(3, 1))
        kinds = [p.get(3, 1) for p in pieces]
        if kinds.count(6) != 256:
            raise ValueError("a model with byte fallback is needed")
        texts = [p[1].decode() for p in pieces]
        #: Normalised bytes under each piece: a control piece stands for none, a fallback piece for one.
        self.width = np.array([{3: 0, 6: 1}.get(k, len(t.encode())) for k, t in zip(kinds, texts, strict=True)], np.int64)

    def spans(self, text: str, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where the piece of each id (begin and end ids among them) begins and ends in the source's UTF-8 bytes."""
        plain, origin = self.map.apply(text.encode("utf-8"))
        wide = np.where(np.frombuffer(plain, np.uint8) == 0x20, 3, 1)
        starts = np.append(np.repeat(origin[:-1], wide), origin[-1])
        if self.prefix and plain:
            starts = np.concatenate([np.zeros(3, np.int64), starts])
        at = np.cumsum(self.width[ids])
        if at[-1] != len(starts) - 1:
            raise AssertionError("pieces do not cover the normalised text")
        return starts[np.concatenate([[0], at[:-1]])].astype("<i4"), starts[at].astype("<i4")

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        """Ids with begin and end ids, without sampling."""
        return [np.array(x, "<u4") for x in self.library.encode(texts, add_bos=True, add_eos=True, num_threads=1)]

    def decode(self, ids: list[np.ndarray]) -> list[str]:
        return self.library.decode([x.tolist() for x in ids], num_threads=1)


SCHEMA = "doc_id long, ids binary, begins binary, ends binary, decoded string"


def encode_documents(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs``: piece ids, source byte spans, and the text decoded from the ids.

    ``ids`` are little-endian unsigned 32-bit integers with begin and end ids;
    ``begins`` and ``ends`` are little-endian signed 32-bit offsets into the UTF-8
    source, one for each id (the begin id covers nothing at 0, the end id nothing at
    the end). A null text counts as empty. Repeated rows and null ids are kept, an
    empty table gives none, other columns are ignored. The model is read once on the
    driver and travels with the tasks.
    """
    with open(model_path, "rb") as f:
        model = docs.sparkSession.sparkContext.broadcast(f.read())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = Encoder(model.value)
        names = ["doc_id", "ids", "begins", "ends", "decoded"]
        kinds = [pa.int64(), pa.binary(), pa.binary(), pa.binary(), pa.string()]

        def some(keys: list, texts: list[str]) -> pa.RecordBatch:
            ids = enc.encode(texts)
            spans = [enc.spans(t, i) for t, i in zip(texts, ids, strict=True)]
            columns = [keys, [i.tobytes() for i in ids], [b.tobytes() for b, _ in spans], [e.tobytes() for _, e in spans], enc.decode(ids)]
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names)

        for batch in batches:
            keys, texts, held = [], [], 0
            for key, text in zip(*batch.columns, strict=True):
                keys.append(key.as_py())
                texts.append(text.as_py() or "")
                held += len(texts[-1])
                if held > BATCH_CHARS:
                    yield some(keys, texts)
                    keys, texts, held = [], [], 0
            if keys:
                yield some(keys, texts)

    rows = docs.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.col(f"`{text_col}`").cast("string").alias("text"))
    return rows.mapInArrow(run, SCHEMA)


def digests(encoded: DataFrame, *more: str) -> DataFrame:
    """Digest columns of ``encode_documents``, and the columns named in ``more`` as they are."""
    return encoded.select(
        "doc_id",
        F.expr("cast(length(ids) / 4 as bigint)").alias("n_tokens"),
        F.sha2("ids", 256).alias("ids_sha256"),
        F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"),
        F.sha2(F.concat("begins", "ends"), 256).alias("spans_sha256"),
        *more,
    )
