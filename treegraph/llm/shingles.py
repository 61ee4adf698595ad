"""Vectorised word shingles: whole Arrow batches of text to sorted token sets, without a Python loop over words.

Words are runs of bytes other than ASCII white space (0x20, 0x09-0x0D) after lower-casing A-Z. A token is the 64-bit hash of
`width` consecutive words; an item (a document, or a line of one) with fewer words is one token, its whole sequence.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

U = np.uint64
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_rng = np.random.default_rng(20240229)
#: Words of at most PLACES bytes are hashed by a table of random numbers, one for each byte at each place; longer ones by BLAKE2.
PLACES = 32
_TABLE = _rng.integers(0, 2**64, PLACES * 256, dtype=np.uint64)
_PLACE = _rng.integers(1, 2**63, 64, dtype=np.uint64) * U(2) + U(1)
#: Bits of a token that a head shows: the first ones, so that the order of tokens stays.
HEAD_BITS = 48
CHUNK_BYTES, CHUNK_ITEMS = 1 << 18, 60_000


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit words."""
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


@dataclass
class Items:
    """Token sets of consecutive items: tokens[start[i]:start[i] + size[i]] is ascending."""

    row: np.ndarray
    line: np.ndarray
    words: np.ndarray
    size: np.ndarray
    start: np.ndarray
    tokens: np.ndarray
    s1: np.ndarray
    s2: np.ndarray


def word_hashes(raw: np.ndarray, item_start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of the words of raw and the item that each is in; no word runs over the start of an item."""
    n = len(raw)
    solid = ~_SPACE[raw]
    first, last = solid.copy(), solid.copy()
    first[1:] &= ~solid[:-1]
    last[:-1] &= ~solid[1:]
    inner = item_start[(item_start > 0) & (item_start < n)]
    first[inner] = solid[inner]
    last[inner - 1] = solid[inner - 1]
    begin, end = np.flatnonzero(first), np.flatnonzero(last) + 1
    if not len(begin):
        return np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64)
    size = end - begin
    at = np.cumsum(size) - size
    place = np.minimum(np.arange(at[-1] + size[-1]) - np.repeat(at, size), PLACES - 1)
    h = np.add.reduceat(_TABLE[place << 8 | _LOWER[raw[solid]]], at)
    h = mix(h + size.astype(np.uint64) * _PLACE[42])
    for i in np.flatnonzero(size > PLACES).tolist():
        h[i] = int.from_bytes(hashlib.blake2b(_LOWER[raw[begin[i] : end[i]]].tobytes(), digest_size=8).digest(), "little")
    return h, np.searchsorted(item_start, begin, "right") - 1


def chunk_items(raw: np.ndarray, row_start: np.ndarray, width: int, by_line: bool) -> Items:
    if by_line:
        breaks = np.flatnonzero(raw == 10) + 1
        item_start = np.concatenate([row_start, breaks])
        row = np.concatenate([np.arange(len(row_start)), np.searchsorted(row_start, breaks - 1, "right") - 1])
        order = np.lexsort((item_start, row))
        item_start, row = item_start[order], row[order]
        line = np.arange(len(row)) - np.searchsorted(row, row, "left")
    else:
        item_start, row, line = row_start, np.arange(len(row_start)), np.zeros(len(row_start), dtype=np.int64)
    n_items = len(item_start)
    h, item = word_hashes(raw, item_start)
    words = np.bincount(item, minlength=n_items)
    token, owner = np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64)
    if len(h) >= width:
        last = len(h) - width + 1
        whole = np.flatnonzero(item[:last] == item[width - 1 :])
        acc = h[:last] * _PLACE[0]
        for k in range(1, width):
            acc += h[k : last + k] * _PLACE[k]
        token, owner = mix(acc[whole]), item[whole]
    short = np.flatnonzero((words > 0) & (words < width))
    if len(short):
        at = np.searchsorted(item, short, "left")
        acc = words[short].astype(np.uint64) * _PLACE[width]
        for k in range(width - 1):
            more = words[short] > k
            acc[more] += h[at[more] + k] * _PLACE[width + 1 + k]
        token, owner = np.concatenate([token, mix(acc)]), np.concatenate([owner, short])
    key = (owner.astype(np.uint64) << U(HEAD_BITS)) | (token >> U(64 - HEAD_BITS))
    order = np.argsort(key)
    key, owner, token = key[order], owner[order], token[order]
    if len(key):
        new = np.concatenate([[True], token[1:] != token[:-1]])
        if (new[1:] & (key[1:] == key[:-1])).any():  # tokens alike in their first bits alone: sort by all
            order = np.lexsort((token, owner))
            owner, token = owner[order], token[order]
            new = np.concatenate([[True], token[1:] != token[:-1]])
        new[1:] |= owner[1:] != owner[:-1]
        owner, token = owner[new], token[new]
    size = np.bincount(owner, minlength=n_items)
    start = np.cumsum(size) - size
    s1, s2 = np.zeros(n_items, dtype=np.uint64), np.zeros(n_items, dtype=np.uint64)
    full = np.flatnonzero(size)
    if len(full):
        s1[full] = np.add.reduceat(mix(token + _PLACE[40]), start[full])
        s2[full] = np.add.reduceat(mix(token ^ _PLACE[41]), start[full])
    return Items(row, line, words, size, start, token, s1.view(np.int64), s2.view(np.int64))


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string column; a null is an empty text."""
    column = column.cast(pa.large_binary())
    if column.null_count:
        column = column.fill_null(b"")
    _, offsets, data = column.buffers()
    ends = np.frombuffer(offsets, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    return (np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, dtype=np.uint8)), ends


def batches(column: pa.Array, width: int, by_line: bool):
    """(first row, Items) for pieces of the column of about CHUNK_BYTES."""
    data, ends = text_buffer(column)
    at, n = 0, len(column)
    while at < n:
        to = int(np.searchsorted(ends, ends[at] + CHUNK_BYTES, "right")) - 1
        to = min(max(to, at + 1), n, at + CHUNK_ITEMS)
        if by_line:
            while to > at + 1 and to - at + np.count_nonzero(data[ends[at] : ends[to]] == 10) > CHUNK_ITEMS:
                to = at + (to - at) // 2
        piece = data[ends[at] : ends[to]]
        if by_line and to == at + 1 and (lines := np.flatnonzero(piece == 10)).size >= CHUNK_ITEMS:
            begin, done = 0, 0  # one text of very many lines: some lines at a time
            while done <= lines.size:
                stop = min(done + CHUNK_ITEMS - 1, lines.size)
                end = int(lines[stop]) if stop < lines.size else len(piece)
                items = chunk_items(piece[begin:end], np.zeros(1, dtype=np.int64), width, True)
                items.line = items.line + done
                yield at, items
                begin, done = end + 1, stop + 1
        else:
            yield at, chunk_items(piece, (ends[at:to] - ends[at]).astype(np.int64), width, by_line)
        at = to


def take_heads(items: Items, length: np.ndarray, full: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Offsets and values of the first length[i] tokens of each item; the first bits of each unless full."""
    offsets = np.concatenate([[0], np.cumsum(length)])
    index = np.arange(offsets[-1]) + np.repeat(items.start - offsets[:-1], length)
    tokens = items.tokens[index]
    return offsets, (tokens if full else tokens >> U(64 - HEAD_BITS)).view(np.int64)
