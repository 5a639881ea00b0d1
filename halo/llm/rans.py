"""Static range asymmetric numeral coding of token ids, vectorised over interleaved lanes.

A block of n ids is dealt to L lanes, id i to lane i mod L, so that one numpy step codes a row of L
ids. All blocks share one frequency table. States are 64 bits wide and give out 32-bit words. Every
`every` rows the lane states and the word position are recorded, so the segments between two such
checkpoints can be decoded at the same time (here: as further lanes of the same numpy step) or alone.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np

# Fixed values of the block format.
MAGIC = b"HRN1"
HEADER = struct.Struct("<4sIIQIIII")  # magic, lanes, rows between checkpoints, ids, words, segments, crc of ids, crc of words
LOW = 1 << 31
MAX_LANES = 8192
ROWS_EACH = 256

U = np.uint64


def scaled_table(counts: np.ndarray, scale_bits: int) -> np.ndarray:
    """Frequencies of sum 2^scale_bits, at least 1 for every symbol that occurs. Exact integer arithmetic."""
    total, room = int(counts.sum()), 1 << scale_bits
    used = np.flatnonzero(counts)
    if len(used) > room:
        raise ValueError("more symbols than the scale has slots")
    freq = np.zeros(len(counts), np.int64)
    if not total:
        return freq
    exact = counts[used].astype(object) * (room - len(used))
    freq[used] = 1 + (exact // total).astype(np.int64)
    left = room - int(freq.sum())
    order = used[np.lexsort((used, -counts[used]))]
    freq[order[0]] += left
    return freq


class Table:
    """A shared frequency table with what coding needs."""

    def __init__(self, freq: np.ndarray, scale_bits: int):
        self.bits = scale_bits
        self.freq = freq.astype(U)
        self.start = np.concatenate([[0], np.cumsum(freq)[:-1]]).astype(U)
        self.symbol = np.repeat(np.arange(len(freq), dtype=np.uint32), freq)

    def to_bytes(self) -> bytes:
        raw = zlib.compress(self.freq.astype("<u4").tobytes(), 6)
        return struct.pack("<II", self.bits, zlib.crc32(raw)) + raw

    @staticmethod
    def from_bytes(data: bytes) -> "Table":
        bits, crc = struct.unpack_from("<II", data)
        if zlib.crc32(data[8:]) != crc:
            raise ValueError("frequency table is damaged")
        return Table(np.frombuffer(zlib.decompress(data[8:]), "<u4").astype(np.int64), bits)


def encode_block(ids: np.ndarray, table: Table, lanes: int | None = None, every: int = ROWS_EACH) -> bytes:
    n = len(ids)
    lanes = lanes or int(min(MAX_LANES, max(1, n // 64)))
    rows = -(-n // lanes)
    state = np.full(lanes, LOW, U)
    out: list[np.ndarray] = [np.zeros(0, np.uint32)] * rows
    marks: dict[int, np.ndarray] = {}
    freq, start, bits = table.freq, table.start, U(table.bits)
    if n and not freq[ids].all():
        raise ValueError("an id is missing from the frequency table")
    step = U((LOW >> table.bits) << 32)
    for r in range(rows - 1, -1, -1):
        part = ids[r * lanes : (r + 1) * lanes]
        k = len(part)
        x, f = state[:k], freq[part]
        full = x >= step * f
        out[r] = (x[full] & U(0xFFFFFFFF)).astype(np.uint32)
        x = np.where(full, x >> U(32), x)
        q = x // f
        state[:k] = (q << bits) + (x - q * f) + start[part]
        if r % every == 0:
            marks[r] = state.copy()
    words = np.concatenate(out) if rows else np.zeros(0, np.uint32)
    sizes = np.fromiter((len(w) for w in out), np.int64, rows)
    begins = np.concatenate([[0], np.cumsum(sizes)])
    segments = sorted(marks)
    raw = words.astype("<u4").tobytes()
    points = np.array([begins[r] for r in segments], "<u8").tobytes() + b"".join(marks[r].astype("<u8").tobytes() for r in segments)
    head = HEADER.pack(MAGIC, lanes, every, n, len(words), len(segments), zlib.crc32(ids.astype("<u4").tobytes()), zlib.crc32(raw))
    return head + points + raw


def read_header(data: bytes) -> dict:
    magic, lanes, every, n, words, segments, crc_ids, crc_words = HEADER.unpack_from(data)
    if magic != MAGIC:
        raise ValueError("not a block")
    return {"lanes": lanes, "every": every, "n": n, "words": words, "segments": segments, "crc_ids": crc_ids, "crc_words": crc_words}


def decode_block(data: bytes, table: Table, segment: int | None = None) -> np.ndarray:
    """All ids of a block, or those of one segment; checksums of the words and of all ids are verified."""
    h = read_header(data)
    lanes, every, n, count = h["lanes"], h["every"], h["n"], h["segments"]
    at = HEADER.size
    begins = np.frombuffer(data, "<u8", count, at).astype(np.int64)
    states = np.frombuffer(data, "<u8", count * lanes, at + 8 * count).reshape(count, lanes)
    raw = data[at + 8 * count * (1 + lanes) :]
    if zlib.crc32(raw) != h["crc_words"] or len(raw) != 4 * h["words"]:
        raise ValueError("block is damaged")
    words = np.frombuffer(raw, "<u4")
    chosen = range(count) if segment is None else [segment]
    parts = _decode_segments(words, states[list(chosen)].astype(U), begins[list(chosen)], [min(n, (s + 1) * every * lanes) - s * every * lanes for s in chosen], lanes, table)
    ids = np.concatenate(parts) if parts else np.zeros(0, np.uint32)
    if segment is None and zlib.crc32(ids.astype("<u4").tobytes()) != h["crc_ids"]:
        raise ValueError("decoded ids do not match their checksum")
    return ids


def _decode_segments(words, states, begins, sizes, lanes, table) -> list[np.ndarray]:
    """Decode segments side by side. `states` has one row of lanes for each segment."""
    mask, bits = U((1 << table.bits) - 1), U(table.bits)
    out = [np.zeros(s, np.uint32) for s in sizes]
    state, place = states.copy(), begins.copy()
    rows = max((-(-s // lanes) for s in sizes), default=0)
    lane = np.arange(lanes)
    for r in range(rows):
        left = np.array([s - r * lanes for s in sizes])
        live = lane[None, :] < left[:, None]
        slot = state & mask
        sym = table.symbol[slot]
        x = table.freq[sym] * (state >> bits) + slot - table.start[sym]
        need = (x < U(LOW)) & live
        taken = need.sum(axis=1)
        where = place[:, None] + np.cumsum(need, axis=1) - 1
        x[need] = (x[need] << U(32)) | words[where[need]].astype(U)
        state = np.where(live, x, state)
        place += taken
        for k in range(len(sizes)):
            m = min(lanes, left[k])
            if m > 0:
                out[k][r * lanes : r * lanes + m] = sym[k, :m]
    return out
