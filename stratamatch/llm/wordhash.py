"""Vectorised word and shingle hashes over UTF-8 bytes.

Words are maximal runs of bytes other than 0x20 and 0x09-0x0D. A word's hash mixes its
bytes eight at a time (a bijection of the word up to eight bytes; words above 64
bytes take a cryptographic digest), so no arithmetic pattern of letters collides. A
run of words has a Rabin-Karp polynomial modulo the prime 2**61 - 1 and a second one
modulo 2**64, over independent word hashes where ``lanes`` is 2. All are fixed
functions of the text, alike in every process.
"""

from __future__ import annotations

import hashlib

import numpy as np

_PIECE, _RUN = 1 << 18, 1 << 14  # bytes and words worked on at once, so that arrays stay in the cache


def _mix(x):
    """Finalise 64-bit values so that all bits depend on all bits."""
    x = x.copy()
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _space_table():
    table = np.zeros(256, dtype=bool)
    table[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
    return table


_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
_LANES = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD1B54A32D192ED03))
_LONG_WORD = 64


class WordHasher:
    """Hashes the words of byte strings: one column, or two independent ones with ``lanes=2``."""

    def __init__(self, lower: bool = False, lanes: int = 1):
        self.space, self.lower, self.lanes = _space_table(), lower, lanes

    def words(self, data: bytes):
        """(hashes, starts, ends) of the words in ``data``, by byte offset; hashes are (n,), or
        (n, 2) with two lanes."""
        if self.lower:
            data = data.translate(_LOWER)
        raw = np.frombuffer(data, dtype=np.uint8)
        out, at = [], 0
        while at < len(raw):
            end = min(at + _PIECE, len(raw))
            while end < len(raw) and not self.space[raw[end - 1]]:  # cut only after white space
                gaps = np.flatnonzero(self.space[raw[end : end + _PIECE]])
                end = end + int(gaps[0]) + 1 if len(gaps) else min(end + _PIECE, len(raw))
            out.append(self._piece(raw[at:end], at))
            at = end
        if not out:
            none = np.zeros(0, dtype=np.int64)
            return np.zeros((0, 2)[: self.lanes], dtype=np.uint64), none, none
        return tuple(np.concatenate(x) for x in zip(*out))

    def _piece(self, raw, at):
        inside = np.zeros(len(raw) + 2, dtype=np.int8)
        inside[1:-1] = ~self.space[raw]
        edge = np.diff(inside)
        starts, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
        sizes = ends - starts
        padded = raw.tobytes() + bytes(8)
        eight = np.ndarray(shape=(len(raw) + 1,), dtype="<u8", buffer=padded, strides=(1,))  # eight bytes from each place
        lanes = [_mix(sizes.astype(np.uint64) * k + k) for k in _LANES[: self.lanes]]
        active, done = slice(None), 0
        while done < _LONG_WORD:  # one round for each eight bytes of the longest word
            left = sizes[active] - done
            block = eight[starts[active] + done]
            short = np.maximum(8 - left, 0).astype(np.uint64) * np.uint64(8)
            block = (block << short) >> short
            for h, k in zip(lanes, _LANES):
                h[active] = _mix((h[active] ^ block) * k + (block >> np.uint64(32)))
            done += 8
            active = np.flatnonzero(sizes > done)
            if not len(active):
                break
        for i in np.flatnonzero(sizes > _LONG_WORD):
            whole = np.frombuffer(hashlib.blake2b(padded[starts[i] : ends[i]], digest_size=16).digest(), dtype="<u8")
            for h, w in zip(lanes, whole):
                h[i] = w
        return lanes[0] if self.lanes == 1 else np.stack(lanes, axis=1), starts + at, ends + at


_PRIME_61 = np.uint64((1 << 61) - 1)
_BASE_61, _BASE_64 = 0x0F1357AEA2E62A9C5 & ((1 << 61) - 1), 0xD1342543DE82EF95


def _fold(x):
    return (x & _PRIME_61) + (x >> np.uint64(61))


def _times_61(a, b: int):
    """a * b modulo 2**61 - 1, by halves of 32 bits."""
    low = np.uint64(0xFFFFFFFF)
    a1, a0, b1, b0 = a >> np.uint64(32), a & low, np.uint64(b >> 32), np.uint64(b & 0xFFFFFFFF)
    middle = a1 * b0 + a0 * b1
    out = (a1 * b1 << np.uint64(3)) + (middle >> np.uint64(29)) + ((middle & np.uint64((1 << 29) - 1)) << np.uint64(32)) + _fold(a0 * b0)
    return _fold(out)


def _polynomials(words, width, times, fold, base, modulus):
    """The polynomial of every run of ``width`` values, from runs of 1, 2, 4, ... values."""
    out, size, run, step = None, 0, words, 1
    while True:
        if width & step:  # runs of the higher bits go after those already joined
            n = len(words) - size - step + 1
            out = run[:n] if out is None else fold(times(run[:n], pow(base, size, modulus)) + out[step : step + n])
            size += step
        if size == width:
            return out
        run = fold(times(run[: len(run) - step], pow(base, step, modulus)) + run[step:])
        step *= 2


def windows(words, width, checks=False):
    """Rabin-Karp hash of each run of ``width`` consecutive word hashes; with ``checks`` also a
    second, independent hash of each."""
    if len(words) < width:
        none = np.zeros(0, dtype=np.uint64)
        return (none, none) if checks else none
    if len(words) > 2 * (_RUN + width):
        parts = [windows(words[i : i + _RUN + width - 1], width, True) for i in range(0, len(words) - width + 1, _RUN)]
        key, check = (np.concatenate(x) for x in zip(*parts))
        return (key, check) if checks else key
    first, second = (words, words) if words.ndim == 1 else (np.ascontiguousarray(words[:, 0]), np.ascontiguousarray(words[:, 1]))
    a = _fold(_polynomials(_fold(_fold(first)), width, _times_61, _fold, _BASE_61, (1 << 61) - 1))
    a = np.where(a >= _PRIME_61, a - _PRIME_61, a)
    b = _polynomials(second, width, lambda x, y: x * np.uint64(y), lambda x: x, _BASE_64, 1 << 64)
    key = _mix(a << np.uint64(3) | b >> np.uint64(61))
    return (key, _mix(b)) if checks else key


def encoded(texts, most=1 << 20):
    """Cut a list of texts (bytes, str or None) into runs of about ``most`` bytes: (first, blobs)."""
    run, size, first = [], 0, 0
    for i, text in enumerate(texts):
        blob = text if isinstance(text, bytes) else text.encode("utf-8", "surrogatepass") if isinstance(text, str) else b""
        if run and size + len(blob) > most:
            yield first, run
            run, size, first = [], 0, i
        run.append(blob)
        size += len(blob) + 1
    if run:
        yield first, run


def portions(batches, column, most=4 << 20):
    """Cut Arrow batches into slices of about ``most`` bytes of ``column``; memory that a
    slice's work leaves unused goes back to the system, as workers live on."""
    import pyarrow.compute as pc

    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = pc.fill_null(pc.binary_length(batch.column(batch.schema.get_field_index(column))), 0).to_numpy(zero_copy_only=False)
        edge = cuts(np.cumsum(sizes.astype(np.int64) + 64) // most)
        for a, b in zip(edge[:-1], edge[1:]):
            yield batch.slice(int(a), int(b - a))
            give_back()


def give_back():
    """Return the worker's unused memory to the system."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


def blobs(batch, column):
    """A string column of an Arrow batch as a list of bytes and None."""
    import pyarrow as pa

    return batch.column(batch.schema.get_field_index(column)).cast(pa.binary()).to_pylist()


def hashed_runs(texts, hasher, most=1 << 20):
    """For each run: (first, blobs, word hashes, starts, ends, word offset of each text)."""
    for first, blobs in encoded(texts, most):
        data = b"\n".join(blobs)
        hashes, starts, ends = hasher.words(data)
        begin = np.zeros(len(blobs) + 1, dtype=np.int64)
        begin[1:] = np.cumsum([len(b) + 1 for b in blobs])
        yield first, data, hashes, starts, ends, np.searchsorted(starts, begin)


def text_windows(hashes, bounds, width, checks=False):
    """Window hashes that stay inside one text: (hashes, word index, text index), then the second hashes."""
    found = windows(hashes, width, checks)
    found = found if checks else (found,)
    counts = np.diff(bounds)
    owner = np.repeat(np.arange(len(counts)), counts)
    at = np.arange(len(found[0]))
    keep = at + width <= bounds[owner[: len(at)] + 1]
    return found[0][keep], at[keep], owner[: len(at)][keep], *(x[keep] for x in found[1:])


def pack(*arrays) -> bytes:
    """Length-prefixed concatenation of arrays."""
    head = np.array([len(arrays), *map(len, arrays)], dtype=np.int64)
    return b"".join([head.tobytes(), *(np.ascontiguousarray(a).tobytes() for a in arrays)])


def unpack(blob: bytes, *kinds):
    """The arrays of ``pack``, with the given dtypes."""
    n = int(np.frombuffer(blob, dtype=np.int64, count=1)[0])
    lengths = np.frombuffer(blob, dtype=np.int64, count=n, offset=8)
    out, at = [], 8 * (n + 1)
    for size, kind in zip(lengths, kinds):
        out.append(np.frombuffer(blob, dtype=kind, count=int(size), offset=at))
        at += np.dtype(kind).itemsize * int(size)
    return out


def pack_rows(ids, known, columns) -> bytes:
    """Compressed rows: ids, whether they are known, and columns of bytes or None."""
    import zstandard

    sizes = [np.array([-1 if x is None else len(x) for x in c], dtype=np.int64) for c in columns]
    body = pack(np.asarray(ids, dtype=np.int64), np.asarray(known, dtype=np.int64), *sizes)
    return zstandard.ZstdCompressor(level=3).compress(b"".join([body, *(x for c in columns for x in c if x)]))


def unpack_rows(blob: bytes, columns: int):
    """The ids (None if unknown) and columns of ``pack_rows``."""
    import zstandard

    data = zstandard.ZstdDecompressor().decompress(blob)
    ids, known, *sizes = unpack(data, *[np.int64] * (2 + columns))
    at, out = 8 * (3 + columns + len(ids) * (2 + columns)), []
    for size in sizes:
        column = []
        for n in size.tolist():
            column.append(None if n < 0 else data[at : at + n])
            at += max(n, 0)
        out.append(column)
    return [i if k else None for i, k in zip(ids.tolist(), known.tolist())], out


def cuts(*sorted_keys):
    """Bounds of the runs of equal values in sorted arrays, with both ends."""
    if not len(sorted_keys[0]):
        return np.zeros(1, dtype=np.int64)
    change = sorted_keys[0][1:] != sorted_keys[0][:-1]
    for other in sorted_keys[1:]:
        change |= other[1:] != other[:-1]
    return np.concatenate([[0], np.flatnonzero(change) + 1, [len(sorted_keys[0])]])


def bucket_of(keys, n):
    """Bucket 0..n-1 of uniform 64-bit hashes, rising with the hash."""
    return ((keys >> np.uint64(32)) * np.uint64(n) >> np.uint64(32)).astype(np.int64)


def spread(ids, n):
    """Bucket 0..n-1 of any integer ids."""
    return bucket_of(_mix(np.asarray(ids).astype(np.int64).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(7)), n)


_PRIME = 2147483647


def part_of(ids, n):
    """Part 0..n-1 of integer ids."""
    return (np.mod(np.asarray(ids, dtype=np.int64), _PRIME) * 48271 % _PRIME) % n
