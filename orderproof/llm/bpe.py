"""Byte-level BPE over Arrow text: vocabularies, and encoding of distinct pieces only."""

from __future__ import annotations

import base64
from functools import lru_cache

import numpy as np
import pyarrow as pa

from orderproof.llm.common import from_buffers, text_buffers

#: Pieces whose ids a worker remembers.
CACHE = 300_000
#: Last bytes of white space characters above ASCII: no unit ends after one of these.
SPACE_ENDS = bytes([*range(0x80, 0x8B), 0x9F, 0xA0, 0xA8, 0xA9, 0xAF])


@lru_cache(maxsize=4)
def ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


@lru_cache(maxsize=4)
def token_table(path: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and size of each id's bytes, and all bytes one after the other."""
    of = {i: b for b, i in ranks(path).items()}
    size = np.array([len(of.get(i, b"")) for i in range(max(of) + 1)], np.int64)
    return np.cumsum(size) - size, size, np.frombuffer(b"".join(of.get(i, b"") for i in range(len(size))), np.uint8)


class Encoder:
    """Ids of strings by a rank file; a worker keeps one for each file."""

    def __init__(self, path: str, pattern: str):
        import tiktoken

        self.enc = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks(path), special_tokens={})
        self.known: dict[str, tuple] = {}

    def encode(self, text: str):
        return self.enc.encode_ordinary(text)

    def of(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(number of ids of each piece, all ids)."""
        if len(self.known) > CACHE:
            self.known.clear()
        out, known = [], self.known
        for p in pieces:
            v = known.get(p)
            if v is None:
                v = known[p] = self.encode(p)
            out.append(v)
        n = np.fromiter(map(len, out), np.int64, len(out))
        return n, np.fromiter((i for v in out for i in v), np.uint32, int(n.sum()))

    def of_all(self, pieces: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """As of(), for an Arrow array; every distinct piece is encoded once."""
        if not len(pieces):
            return np.zeros(0, np.int64), np.zeros(0, np.uint32)
        d = pieces.dictionary_encode()
        n, ids = self.of(d.dictionary.to_pylist())
        start = np.concatenate([[0], np.cumsum(n)[:-1]])
        at = d.indices.to_numpy()
        count = n[at]
        return count, ids[np.repeat(start[at] - np.concatenate([[0], np.cumsum(count)[:-1]]), count) + np.arange(count.sum())]


class SpecialEncoder(Encoder):
    """By a tokenizers file whose ranks are also at hand: only units that hold a special token go through the slower library."""

    def __init__(self, json_path: str, path: str, pattern: str):
        from tokenizers import Tokenizer

        super().__init__(path, pattern)
        self.whole = Tokenizer.from_file(json_path)
        self.special = [str(t.content) for t in self.whole.get_added_tokens_decoder().values()]

    def encode(self, text: str):
        if any(s in text for s in self.special):
            return self.whole.encode(text, add_special_tokens=False).ids
        return self.enc.encode_ordinary(text)


@lru_cache(maxsize=4)
def encoder(path: str, pattern: str) -> Encoder:
    return Encoder(path, pattern)


@lru_cache(maxsize=4)
def special_encoder(json_path: str, path: str, pattern: str) -> SpecialEncoder:
    return SpecialEncoder(json_path, path, pattern)


def units(text: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """Texts cut before each ASCII space that follows another character, and the number of units of each text.

    No match of the byte-level pattern reaches over such a cut: a match ends where its letters, digits or signs end, and white
    space is taken together with what comes after it.
    """
    off, data = text_buffers(text)
    space = (data == 32) | ((data >= 9) & (data <= 13))
    cut = np.zeros(len(data) + 1, bool)
    if len(data):
        ends_space = np.zeros(256, bool)
        ends_space[: 0x21] = True
        ends_space[np.frombuffer(SPACE_ENDS, np.uint8)] = True
        cut[1:-1] = space[1:] & ~ends_space[data[:-1]]
    cut[off] = True
    cut[-1] = True
    at = np.flatnonzero(cut)
    if len(at) == 1:
        return pa.array([], pa.large_string()), np.zeros(len(off) - 1, np.int64)
    return from_buffers(at, data), np.diff(np.searchsorted(at, off))


def encode_texts(text: pa.Array, enc: Encoder) -> tuple[np.ndarray, np.ndarray]:
    """(number of ids of each text, all ids)."""
    parts, count = units(text)
    n, ids = enc.of_all(parts)
    ends = np.concatenate([[0], np.cumsum(n)])
    at = np.concatenate([[0], np.cumsum(count)])
    return ends[at[1:]] - ends[at[:-1]], ids


def binaries(count: np.ndarray, ids: np.ndarray, kind: str) -> pa.Array:
    """One binary value of little-endian integers per row."""
    raw = ids.astype(kind)
    off = np.concatenate([[0], np.cumsum(count)]) * raw.dtype.itemsize
    return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(count), [None, pa.py_buffer(np.ascontiguousarray(off, np.int64)), pa.py_buffer(raw.tobytes())]).cast(pa.binary())
