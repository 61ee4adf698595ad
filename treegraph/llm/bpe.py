"""Byte-level BPE through a sentencepiece model that is written, not trained: encoding to ids and back."""

from __future__ import annotations

import base64
import re
import struct
from itertools import chain

import numpy as np
import public_tokenizers
import pyarrow as pa
import pyarrow.compute as pc
import regex
import sentencepiece
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

def byte_alphabet() -> list[str]:
    """A printable character for each byte: itself where Latin-1 prints it, else the next one from U+0100 on."""
    printable = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(0x100, 0x200))
    return [chr(b) if b in printable else chr(next(spare)) for b in range(256)]


def read_ranks(raw: bytes) -> dict[bytes, int]:
    """The lines of a rank file: a token in base64 and its rank."""
    return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in raw.splitlines() if line.strip())}


def _varint(n: int) -> bytes:
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def _field(number: int, value: bytes | int | float) -> bytes:
    """One protobuf field: bytes are length-delimited, floats 32-bit, ints varints."""
    if isinstance(value, bytes):
        return _varint(number << 3 | 2) + _varint(len(value)) + value
    if isinstance(value, float):
        return _varint(number << 3 | 5) + struct.pack("<f", value)
    return _varint(number << 3) + _varint(value)


def model_bytes(ranks: dict[bytes, int]) -> bytes:
    """A sentencepiece BPE model of the ranks: piece 0 is unknown; piece 1 + i is the i-th token by rank, scored -rank."""
    letters = byte_alphabet()
    out = [_field(1, _field(1, b"<unk>") + _field(2, 0.0) + _field(3, 2))]
    for token, rank in sorted(ranks.items(), key=lambda x: x[1]):
        out.append(_field(1, _field(1, "".join(letters[b] for b in token).encode()) + _field(2, float(-rank)) + _field(3, 1)))
    trainer = _field(3, 2) + _field(4, len(ranks) + 1) + _field(40, 0)  # model type BPE, size, unknown id
    normaliser = _field(1, b"identity") + _field(3, 0) + _field(4, 0) + _field(5, 0)  # no dummy prefix, nothing removed or escaped
    return b"".join([*out, _field(2, trainer), _field(3, normaliser)])


#: Kinds of characters that the public pattern tells apart.
LETTER, NUMBER, BLANK, OTHER = 1, 2, 3, 0
#: Characters between two pieces of one text that the model encodes together; no piece of the vocabulary holds it.
GAP = 0x2581
_kinds: list[np.ndarray] = []


def kinds() -> np.ndarray:
    """The kind of each code point, as the pattern's own engine sees it; built once a process."""
    if not _kinds:
        every = "".join(map(chr, chain(range(0xD800), [0xFFFD] * 0x800, range(0xE000, 0x110000))))
        out = np.zeros(0x110000, dtype=np.uint8)
        for kind, pattern in ((LETTER, r"\p{L}+"), (NUMBER, r"\p{N}+"), (BLANK, r"\s+")):
            for m in regex.finditer(pattern, every):
                out[m.start() : m.end()] = kind
        _kinds.append(out)
    return _kinds[0]


def starts(points: np.ndarray, texts: np.ndarray) -> np.ndarray:
    """Where the pre-tokens of the public pattern start, for code points of texts behind each other that begin at texts.

    A token is a run of one kind. A blank (U+0020) before a run of another kind belongs to it; a longer run of white space
    gives up its last character unless the text ends there; an apostrophe that no blank or mark precedes takes a listed ending.
    """
    n = len(points)
    kind = kinds()[points]
    begin = np.zeros(n + 1, dtype=bool)
    begin[texts] = True
    begin[n] = True
    cut = begin[:n].copy()
    cut[1:] |= kind[1:] != kind[:-1]
    blank = kind == BLANK
    last = blank & np.concatenate([~blank[1:], [True]]) & ~begin[1:]  # the last of a run that does not end its text
    cut |= last
    joined = np.flatnonzero(last & (points == 0x20)) + 1
    cut[joined] = False
    sign = np.flatnonzero((points == 0x27) & cut)
    sign = sign[sign + 1 < n]
    sign = sign[(kind[sign + 1] == LETTER) & ~begin[sign + 1]]
    one = points[sign + 1]
    two = np.where((sign + 2 < n) & ~begin[np.minimum(sign + 2, n)], points[np.minimum(sign + 2, n - 1)], 0)
    size = np.where(np.isin(one, [0x73, 0x74, 0x6D, 0x64]), 1, 0)  # 's 't 'm 'd
    for a, b in ("re", "ve", "ll"):
        size[(one == ord(a)) & (two == ord(b))] = 2
    sign, size = sign[size > 0], size[size > 0]
    cut[sign + 1] = False
    after = sign + 1 + size
    cut[after[after < n]] = True
    return np.flatnonzero(cut)


def gathered(offsets: np.ndarray, values: np.ndarray, pick: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The picked ones of ragged lists, behind each other: their sizes and values."""
    size = (offsets[1:] - offsets[:-1])[pick]
    end = np.cumsum(size)
    return size, values[np.arange(end[-1] if len(end) else 0) + np.repeat(offsets[:-1][pick] - end + size, size)]


class Codec:
    """Encodes and decodes by a rank file; one a worker. It remembers no texts."""

    def __init__(self, raw: bytes, pattern: str):
        ranks = read_ranks(raw)
        order = sorted(ranks, key=ranks.__getitem__)
        self.whole = pa.array(order, pa.large_binary())
        self.ids = np.array([ranks[t] for t in order], dtype=np.int32)
        self.model = sentencepiece.SentencePieceProcessor(model_proto=model_bytes(ranks))
        self.split = None if pattern == public_tokenizers.PATTERN else regex.compile(pattern).findall
        self.letter = np.array([ord(c) for c in byte_alphabet()], dtype=np.uint32)
        top = int(self.ids.max()) + 1
        self.known = np.zeros(top, dtype=bool)
        self.known[self.ids] = True
        size = np.zeros(top, dtype=np.int64)
        size[self.ids] = [len(t) for t in order]
        self.offsets = np.concatenate([[0], np.cumsum(size)])
        self.bytes = np.zeros(self.offsets[-1], dtype=np.uint8)
        for t, i in zip(order, self.ids.tolist()):
            self.bytes[self.offsets[i] : self.offsets[i + 1]] = np.frombuffer(t, dtype=np.uint8)

    def of_distinct(self, tokens: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Offsets and ids of distinct pre-tokens (large_binary): whole from the vocabulary, else by merges."""
        at = pc.index_in(tokens, self.whole)
        absent = pc.is_null(at)
        found = np.asarray(pc.fill_null(at, 0))
        size = np.ones(len(tokens), dtype=np.int64)
        rest = tokens.filter(absent)
        place = np.flatnonzero(np.asarray(absent))
        merged = np.zeros(0, dtype=np.int32)
        if len(rest):
            raw, ends = buffer_of(rest)
            points = np.insert(self.letter[raw[ends[0] : ends[-1]]], ends[1:] - ends[0], GAP)
            pieces = []
            cuts = np.searchsorted(ends - ends[0], np.arange(0, ends[-1] - ends[0], 1 << 15), "right") - 1
            marks = (ends - ends[0] + np.arange(len(ends)))[np.unique(np.append(cuts, len(rest)))]
            for a, b in zip(marks[:-1].tolist(), marks[1:].tolist()):
                pieces += self.model.encode(points[a:b].tobytes().decode("utf-32-le"))
            pieces = np.array(pieces, dtype=np.int64)
            gap = pieces == 0
            merged = self.ids[pieces[~gap] - 1]
            upto = np.flatnonzero(gap)
            size[place] = np.diff(np.concatenate([[-1], upto])) - 1
        offsets = np.concatenate([[0], np.cumsum(size)])
        values = np.empty(offsets[-1], dtype=np.int32)
        values[offsets[:-1]] = self.ids[found]
        if len(rest):
            own = size[place]
            end = np.cumsum(own)
            values[np.arange(end[-1]) + np.repeat(offsets[:-1][place] - end + own, own)] = merged
        return offsets, values

    def pre_tokens(self, raw: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Byte offsets at which pre-tokens of texts start, raw[ends[i]:ends[i + 1]] each; a text's start is one of them."""
        if self.split:
            at = []
            for a, b in zip(ends[:-1].tolist(), ends[1:].tolist()):
                for token in self.split(raw[a:b].tobytes().decode()):
                    at.append(a)
                    a += len(token.encode())
            return np.array(at, dtype=np.int64)
        points = np.frombuffer(raw[ends[0] : ends[-1]].tobytes().decode().encode("utf-32-le"), dtype=np.uint32)
        lead = np.append(np.flatnonzero((raw[ends[0] : ends[-1]] & 0xC0) != 0x80), ends[-1] - ends[0])
        texts = np.searchsorted(lead, (ends[:-1] - ends[0])[ends[1:] > ends[:-1]])
        return lead[starts(points, texts)] + ends[0] if len(points) else np.zeros(0, dtype=np.int64)

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """The number of ids of each text (large_binary without nulls) and all ids behind each other."""
        raw, ends = buffer_of(texts)
        begin = self.pre_tokens(raw, ends)
        if not len(begin):
            return np.zeros(len(texts), dtype=np.int64), np.zeros(0, dtype=np.int32)
        bounds = np.append(begin, ends[-1])
        tokens = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(begin), [None, pa.py_buffer(bounds), pa.py_buffer(raw)])
        coded = tokens.dictionary_encode()
        offsets, values = self.of_distinct(coded.dictionary)
        size, ids = gathered(offsets, values, np.asarray(coded.indices))
        upto = np.concatenate([[0], np.cumsum(size)])
        return np.diff(upto[np.searchsorted(begin, ends)]), ids

    def decode(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The number of bytes of each id, and their bytes behind each other; an id that the vocabulary lacks raises KeyError."""
        if len(ids) and (ids.min() < 0 or ids.max() >= len(self.known) or not self.known[ids].all()):
            raise KeyError("an id that the vocabulary lacks")
        return gathered(self.offsets, self.bytes, ids)


def buffer_of(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a large_binary column without nulls."""
    _, offsets, data = texts.buffers()
    ends = np.frombuffer(offsets, dtype=np.int64)[texts.offset : texts.offset + len(texts) + 1]
    return (np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, dtype=np.uint8)), ends


def slices(sizes: np.ndarray, room: int = 1 << 22):
    """(from, to) of runs of texts of about so many bytes together, so that a worker holds few of them at a time."""
    upto, at = np.cumsum(sizes), 0
    while at < len(sizes):
        to = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + room, "right")))
        yield at, to
        at = to


def parts_of(text: bytes, room: int = 1 << 22):
    """A long text in parts, cut before a blank between ASCII letters or digits, where a pre-token starts in any case."""
    at = 0
    while at < len(text):
        m = _SAFE.search(text, at + room)
        to = m.start() + 1 if m else len(text)
        yield text[at:to]
        at = to


_SAFE = re.compile(rb"[A-Za-z0-9](?= [A-Za-z0-9])")
_codecs: dict[tuple[int, str], Codec] = {}


def codec(raw: bytes, pattern: str) -> Codec:
    key = (hash(raw), pattern)
    if key not in _codecs:
        _codecs[key] = Codec(raw, pattern)
    return _codecs[key]


def functions(spark: SparkSession, path: str | None = None, pattern: str = public_tokenizers.PATTERN):
    """(encode, decode): Column functions, a text to its array of ids and such an array to its bytes (binary).

    The rank file is read once, by the driver, and sent to the workers. A null text is empty: no ids; null ids give no
    bytes. Unpaired surrogates can't occur in Spark's strings; U+0000 and all white space are kept. An id that the file
    lacks raises KeyError.
    """
    with open(path or public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), "rb") as f:
        shared = spark.sparkContext.broadcast(f.read())

    @F.arrow_udf("array<int>")
    def encode(texts: pa.Array) -> pa.Array:
        c = codec(shared.value, pattern)
        texts = pc.fill_null(texts.cast(pa.large_binary()), b"")
        sizes, values = [], []
        for at, to in slices(np.asarray(pc.binary_length(texts))):
            part = texts.slice(at, to - at)
            if to == at + 1 and c.split is None:
                got = [c.encode(pa.array([x], pa.large_binary())) for x in parts_of(part[0].as_py())]
                sizes.append(np.array([sum(len(ids) for _, ids in got)], dtype=np.int64))
                values += [ids for _, ids in got]
            else:
                n, ids = c.encode(part)
                sizes.append(n)
                values.append(ids)
        none = np.zeros(0, dtype=np.int32)
        offsets = np.concatenate([[0], np.cumsum(np.concatenate([none, *sizes]))])
        return pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(np.concatenate([none, *values])))

    @F.arrow_udf("binary")
    def decode(ids: pa.Array) -> pa.Array:
        c = codec(shared.value, pattern)
        out = [pa.array([], pa.binary())]
        lengths = np.asarray(pc.fill_null(pc.list_value_length(ids), 0)).astype(np.int64)
        for at, to in slices(lengths, 1 << 19):
            flat = np.asarray(ids.slice(at, to - at).flatten())
            size, data = c.decode(flat)
            ends = np.concatenate([[0], np.cumsum(size)])[np.concatenate([[0], np.cumsum(lengths[at:to])])]
            out.append(pa.BinaryArray.from_buffers(pa.binary(), to - at, [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(data)]))
        return pa.concat_arrays(out)

    return encode, decode


def encode_texts(docs: DataFrame, *, text_col: str = "text", path: str | None = None, out: str = "ids") -> DataFrame:
    """docs with the ids of each text in column out (replaced if there)."""
    encode, _ = functions(docs.sparkSession, path)
    return docs.withColumn(out, encode(F.col(text_col)))


def decode_ids(docs: DataFrame, *, ids_col: str = "ids", path: str | None = None, out: str = "decoded") -> DataFrame:
    """docs with the bytes of each array of ids in column out (replaced if there)."""
    _, decode = functions(docs.sparkSession, path)
    return docs.withColumn(out, decode(F.col(ids_col)))


def id_digest(ids: Column) -> Column:
    return F.sha2(F.array_join(ids, ",").cast("binary"), 256)


def digests(docs: DataFrame) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of documents."""
    coded = decode_ids(encode_texts(docs.select("doc_id", "text")))
    return coded.select("doc_id", F.size("ids").cast("long").alias("n_tokens"), id_digest(F.col("ids")).alias("ids_sha256"), F.sha2(F.col("decoded"), 256).alias("decoded_sha256"))


def op2_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digests(table(spark, sf_dir, "documents"))


QUERIES = {"op2_byte_bpe": op2_byte_bpe}
ORACLES: dict[str, str] = {}
