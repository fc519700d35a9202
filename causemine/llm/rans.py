"""A range asymmetric numeral system coder over a static table, in interleaved lanes.

A block of ids is laid out in steps of `lanes` ids; each lane has a 64-bit state of its own, and
all lanes share one stream of 32-bit words. numpy codes a whole step at once. Every `every` steps
a checkpoint keeps the states and the place in the stream, so a decoder can begin there.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np

SCALE = 20
_LOW = np.uint64(1 << 31)
_MAGIC = b"RNSB"
_HEAD = struct.Struct("<4sHHIIIIII")  # magic, version, scale, ids, lanes, steps between checkpoints, words, checkpoints, crc


def normalised(counts: np.ndarray, scale: int = SCALE) -> np.ndarray:
    """Frequencies that sum to 2**scale, at least 1 for each id that occurs."""
    counts = np.asarray(counts, np.float64)
    if not counts.sum():
        counts = np.ones_like(counts)
    if np.count_nonzero(counts) > 1 << (scale - 1):
        raise ValueError("too many ids for this scale")
    f = np.where(counts > 0, np.maximum(1, np.floor(counts * ((1 << scale) / counts.sum()))), 0).astype(np.int64)
    over = int(f.sum()) - (1 << scale)
    if over <= 0:
        f[np.argmax(counts)] -= over
        return f
    for i in np.argsort(-f, kind="stable"):  # the raised ones are paid for by the largest
        take = min(over, int(f[i]) - 1, max(1, int(f[i]) // 2))
        f[i] -= take
        over -= take
        if not over:
            break
    return f if not over else normalised(f, scale)


class Table:
    """What coding needs of a table of frequencies: cumulated starts and the id of each slot."""

    def __init__(self, frequencies: np.ndarray, scale: int = SCALE) -> None:
        f = np.asarray(frequencies, np.uint64)
        if int(f.sum()) != 1 << scale:
            raise ValueError("frequencies must sum to a power of two")
        self.scale, self.f = scale, f
        self.start = np.cumsum(f) - f
        self.id_of = np.repeat(np.arange(len(f), dtype=np.uint32), f.astype(np.int64))


def lanes_for(n: int) -> int:
    """More lanes for longer blocks: their states then cost about one percent."""
    return max(4, min(4096, 1 << max(0, (n // 256).bit_length() - 1)))


def encode(ids: np.ndarray, table: Table, lanes: int | None = None, every: int = 128) -> bytes:
    n, lanes = len(ids), lanes or lanes_for(len(ids))
    steps, s = -(-n // lanes), np.uint64(table.scale)
    laid = np.full(steps * lanes, int(np.argmax(table.f)), np.int64)
    laid[:n] = ids
    if n and not table.f[laid].all():
        raise ValueError("an id has no frequency")
    f, start = table.f[laid].reshape(steps, lanes), table.start[laid].reshape(steps, lanes)
    most = f << np.uint64(63 - table.scale)
    x, words, marks, emitted = np.full(lanes, _LOW), [], [], 0
    for t in range(steps - 1, -1, -1):
        full = x >= most[t]
        if full.any():
            words.append(x[full].astype("<u4"))  # the low half
            emitted += len(words[-1])
            x = np.where(full, x >> np.uint64(32), x)
        q = x // f[t]
        x = (q << s) + (x - q * f[t]) + start[t]
        if t and t % every == 0:
            marks.append((emitted, x))
    stream = np.concatenate(words[::-1]) if words else np.empty(0, "<u4")
    out = [_HEAD.pack(_MAGIC, 1, table.scale, n, lanes, every, len(stream), len(marks), zlib.crc32(np.asarray(ids, "<u4").tobytes())), x.astype("<u8").tobytes()]
    for after, states in reversed(marks):
        out += [struct.pack("<I", len(stream) - after), states.astype("<u8").tobytes()]
    return b"".join([*out, stream.tobytes(), b""])


def _parts(block: bytes):
    magic, version, scale, n, lanes, every, n_words, n_marks, crc = _HEAD.unpack_from(block)
    if magic != _MAGIC or version != 1:
        raise ValueError("not a block of this format")
    at = _HEAD.size
    marks = [(0, np.frombuffer(block, "<u8", lanes, at))]
    at += 8 * lanes
    for _ in range(n_marks):
        (word,) = struct.unpack_from("<I", block, at)
        marks.append((word, np.frombuffer(block, "<u8", lanes, at + 4)))
        at += 4 + 8 * lanes
    return scale, n, lanes, every, crc, marks, np.frombuffer(block, "<u4", n_words, at)


def segments(block: bytes) -> int:
    """How many parts of the block can be decoded on their own."""
    return len(_parts(block)[5])


def decode_segment(block: bytes, table: Table, k: int) -> np.ndarray:
    """The ids from checkpoint k to the next."""
    scale, n, lanes, every, _, marks, stream = _parts(block)
    if scale != table.scale:
        raise ValueError("the block was coded with another scale")
    steps = -(-n // lanes)
    first, last = k * every, min(steps, (k + 1) * every) if k + 1 < len(marks) else steps
    s, mask, word = np.uint64(scale), np.uint64((1 << scale) - 1), marks[k][0]
    x, out = marks[k][1].astype(np.uint64), np.empty((last - first, lanes), np.uint32)
    for t in range(last - first):
        slot = x & mask
        found = table.id_of[slot]
        out[t] = found
        x = table.f[found] * (x >> s) + slot - table.start[found]
        low = np.flatnonzero(x < _LOW)
        if len(low):
            x[low] = (x[low] << np.uint64(32)) | stream[word : word + len(low)].astype(np.uint64)
            word += len(low)
    return out.reshape(-1)[: n - first * lanes]


def decode(block: bytes, table: Table) -> np.ndarray:
    """All ids of the block, held against its checksum."""
    n, crc = _parts(block)[1], _parts(block)[4]
    ids = np.concatenate([decode_segment(block, table, k) for k in range(segments(block))]) if n else np.empty(0, np.uint32)
    if zlib.crc32(ids.astype("<u4").tobytes()) != crc:
        raise ValueError("a block does not match its checksum")
    return ids


def blocks(sizes: list[int], most: int) -> Iterator[tuple[int, int]]:
    """Cut a list of document sizes into runs of whole documents with about `most` ids each."""
    first = held = 0
    for i, n in enumerate(sizes):
        held += n
        if held >= most:
            yield first, i + 1
            first, held = i + 1, 0
    if first < len(sizes):
        yield first, len(sizes)
