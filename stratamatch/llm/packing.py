"""Packing of token sequences with balanced attention cost.

Documents are tokenised once; whole sequences' worth of tokens are cut off at once,
and the tails are dealt by hash to groups that grow in number with the input. A group
has as many sequences as its tails' tokens need, so only the last tokens of a group are
padded. Tails in descending length go to the sequence of the lowest cost so far (linear
plus quadratic in each piece's length) among all that have room for them; only a tail
that fits nowhere is cut, to fill the cheapest sequence.

Ids are those of the tokenizer's file. Where the file is a plain byte-level vocabulary
(checked: no normalizer, the usual pieces, merges in the order of their ids) its merges
run in a faster byte-pair engine with the same ids; any other file, and texts that
hold one of its special tokens, go through the tokenizer itself.

Defined results: null and empty texts have the end id only; rows that repeat an id
are packed each; an empty table gives no pieces; null ids are carried.
"""

from __future__ import annotations

import heapq
import json
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .wordhash import give_back, portions

LENGTH, END, LINEAR, QUADRATIC = 2048, 1, 1.0, 1.0 / 2048
#: Documents of a group on average; only their tails, below ``length`` ids each, are held together.
GROUP = 3000
#: The file's own way of cutting texts into pieces before merging (fixed value).
_PIECES = r"""'(?:[sdmt]|ll|ve|re)| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""


def is_plain(file: dict) -> bool:
    """Whether the byte-pair engine with ranks by id gives the ids of this tokenizer file."""
    cut, model = file.get("pre_tokenizer") or {}, file["model"]
    if file.get("normalizer") or cut.get("type") != "ByteLevel" or cut.get("add_prefix_space") or not cut.get("use_regex", True):
        return False
    if model.get("type") != "BPE" or any(model.get(k) for k in ("dropout", "unk_token", "continuing_subword_prefix", "end_of_word_suffix", "byte_fallback", "ignore_merges")):
        return False
    pairs = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
    made = [model["vocab"].get("".join(pair), -1) for pair in pairs]
    special = {t["content"] for t in file.get("added_tokens", ())}
    letters = sum(1 for t in model["vocab"] if len(t) == 1 and t not in special)
    # Every token but the 256 bytes comes from a merge, and earlier merges have smaller ids.
    return letters == 256 and all(a < b for a, b in zip([-1, *made], made)) and len(made) + 256 == len(set(model["vocab"]) - special)


def token_encoder(path: str):
    """A function from a text to its ids (no special tokens added)."""
    from tokenizers import Tokenizer

    with open(path, encoding="utf-8") as f:
        file = json.load(f)
    slow = Tokenizer.from_file(path)
    if not is_plain(file):
        return lambda text: slow.encode(text, add_special_tokens=False).ids
    import tiktoken

    special = {t["content"]: t["id"] for t in file.get("added_tokens", ())}
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]  # bytes that the file writes as themselves
    other = [b for b in range(256) if b not in set(plain)]
    byte = {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(other)}
    ranks = {bytes(byte[c] for c in token): i for token, i in file["model"]["vocab"].items() if token not in special}
    fast = tiktoken.Encoding("from_file", pat_str=_PIECES, mergeable_ranks=ranks, special_tokens={})

    def ids(text: str):
        if any(s in text for s in special):
            return slow.encode(text, add_special_tokens=False).ids
        return fast.encode_ordinary(text)

    return ids


def pack(docs: DataFrame, tokenizer: str, length: int = LENGTH, end: int = END, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, start, length, ids_crc32, doc_tokens, sequence_id, offset for every piece."""
    slim = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    groups = max(1, -(-docs.count() // GROUP))

    def cut(batches):
        encode = token_encoder(tokenizer)
        for batch in portions(batches, "text"):
            out = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                ids = np.append(np.array(encode(text or ""), dtype="<u4"), np.array([end], dtype="<u4"))
                whole, n = len(ids) // length * length, len(ids)
                group = zlib.crc32(f"{doc} {n} {zlib.crc32(ids)}".encode()) % groups
                out.extend((group, doc, a, length, zlib.crc32(ids[a : a + length]), n, None) for a in range(0, whole, length))
                if n > whole:
                    out.append((group, doc, whole, n - whole, None, n, ids[whole:].tobytes()))
                if len(out) >= 2000:
                    yield _rows(out)
                    out = []
            if out:
                yield _rows(out)

    schema = f"{id_col} long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
    names = [x.split()[0] for x in schema.split(", ")]

    def place(table: pa.Table) -> pa.Table:
        give_back()
        return pa.table(list(map(list, zip(*placed_pieces(table, length)))) or [[]] * 7, schema=pa.schema([(n, pa.int64()) for n in names]))

    pieces = slim.mapInArrow(cut, "grp int, id long, start long, length long, crc long, n long, tail binary")
    return pieces.groupBy("grp").applyInArrow(place, schema)


def _rows(out):
    kinds = [pa.int32(), *[pa.int64()] * 5, pa.binary()]
    return pa.RecordBatch.from_arrays([pa.array(c, type=k) for c, k in zip(zip(*out), kinds)], names=["grp", "id", "start", "length", "crc", "n", "tail"])


def placed_pieces(table, length):
    """Final rows of one group."""
    group, doc, start, size, crc, n, tail = (c.to_pylist() for c in table.select(["grp", "id", "start", "length", "crc", "n", "tail"]).columns)
    base, serial = (group[0] if group else 0) << 40, 0
    full = sorted((i for i in range(len(doc)) if tail[i] is None), key=lambda i: (doc[i] is not None, doc[i], n[i], crc[i], start[i]))
    for i in full:
        yield doc[i], start[i], size[i], crc[i], n[i], base + serial, 0
        serial += 1
    rest = sorted((i for i in range(len(doc)) if tail[i] is not None), key=lambda i: (-size[i], doc[i] is not None, doc[i], n[i], tail[i]))
    for k, a, b, sequence, offset in balanced([size[i] for i in rest], length):
        i = rest[k]
        yield doc[i], start[i] + a, b - a, zlib.crc32(tail[i][4 * a : 4 * b]), n[i], base + serial + sequence, offset


def piece_cost(size):
    """Cost estimate of a piece: linear plus quadratic in its length."""
    return LINEAR * size + QUADRATIC * size * size


class _Open:
    """Sequences by their room: the cheapest of all with at least a given room."""

    def __init__(self, length):
        self.top = 1 << length.bit_length()
        self.by_room = [[] for _ in range(self.top)]
        self.least = [(float("inf"), -1)] * (2 * self.top)  # a tree of minima over rooms

    def _raise(self, room):
        i = room + self.top
        self.least[i] = self.by_room[room][0] if self.by_room[room] else (float("inf"), -1)
        while i > 1:
            i //= 2
            self.least[i] = min(self.least[2 * i], self.least[2 * i + 1])

    def add(self, room, cost, sequence):
        heapq.heappush(self.by_room[room], (cost, sequence))
        self._raise(room)

    def take(self, size):
        """(room, cost, sequence) of the cheapest with room for ``size``, taken out; None if there is none."""
        best, node, i = (float("inf"), -1), 0, size + self.top
        if self.least[i] < best:
            best, node = self.least[i], i
        while i > 1:
            if i % 2 == 0 and self.least[i + 1] < best:
                best, node = self.least[i + 1], i + 1
            i //= 2
        if not node:
            return None
        while node < self.top:
            node = 2 * node if self.least[2 * node] == best else 2 * node + 1
        room = node - self.top
        cost, sequence = heapq.heappop(self.by_room[room])
        self._raise(room)
        return room, cost, sequence


def balanced(sizes, length):
    """(item, from, to, sequence, offset) for items of descending size."""
    free = _Open(length)
    for s in range(-(-sum(sizes) // length)):
        free.add(length, 0.0, s)
    for k, size in enumerate(sizes):
        at = 0
        while at < size:
            room, cost, s = free.take(size - at) or free.take(1)
            step = min(size - at, room)
            yield k, at, at + step, s, length - room
            at += step
            if room > step:
                free.add(room - step, cost + piece_cost(step), s)
