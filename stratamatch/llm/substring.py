"""Removal of passages that repeat across documents.

Every window of ``width`` consecutive words is hashed (Rabin-Karp) and counted
by hash; a window whose word sequence also starts in a document with a smaller
id marks its words, and marked words merge into maximal removal intervals.

Plan. One Python pass hashes whole texts and combines within its batch: each
hash leaves a batch once, with its smallest document, so a passage that a third
of all rows share costs one entry a batch. Entries travel as packed arrays by
hash bucket; a bucket answers with the entries that are not the smallest, packed
by document bucket; there texts (compressed on their way) and answers meet and are cut. The
numbers of buckets grow with the input, so that no task holds more than a few
tens of MB.

Equality of word sequences is decided by two independent hashes (a polynomial modulo a
prime, and another modulo 2**64 over other word hashes): all 128 bits within a batch;
between batches 64 bits of the first, 8 of the second, and the bucket, which comes from
other bits of the second, so its bits grow with the input (at 100 TB some 93 in all).

Defined results: a null or empty text has no words; texts under ``width`` words
are kept whole; rows that repeat a doc_id are the same document to each other;
a row whose id is null is kept whole and is never the earlier document.
"""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .durable import slices
from .wordhash import WordHasher, blobs, bucket_of, cuts, give_back, hashed_runs, pack, pack_rows, part_of, portions, text_windows, unpack, unpack_rows

WIDTH = 13


def remove_repeats(docs: DataFrame, width: int = WIDTH, id_col: str = "doc_id", text_col: str = "text", with_text: bool = True, carry=()) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256, intervals (array of [start, end) word
    ranges that go), if ``with_text`` kept_text (the kept words joined by
    one space) and the string columns ``carry``."""
    if width < 1:
        raise ValueError("width must be at least 1")
    extra = [F.col(c).cast("string").alias(f"carry_{i}") for i, c in enumerate(carry)]
    slim = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"), *extra)
    n = slices(slim)
    entries = slim.where("id is not null").select("id", "text").mapInArrow(_entries(width, n), "bucket int, kind int, data binary")
    answers = entries.groupBy("bucket").applyInPandas(_judge(n), "part int, kind int, data binary")
    known = F.col("id").isNotNull()
    texts = slim.select(F.coalesce("id", F.lit(0)).alias("id"), known.alias("known"), *slim.columns[1:]).mapInArrow(_texts(n), "part int, kind int, data binary")
    schema = f"{id_col} long, n_words long, n_removed long, kept_sha256 string, intervals array<array<long>>" + ", kept_text string" * with_text + "".join(f", `{c}` string" for c in carry)
    return texts.unionByName(answers).groupBy("part").applyInPandas(_cut(width, [id_col, "n_words", "n_removed", "kept_sha256", "intervals"] + ["kept_text"] * with_text, list(carry)), schema)


def _entries(width, n):
    def run(batches):
        hasher = WordHasher(lanes=2)
        for batch in portions(batches, "text"):
            ids, texts = batch.column(0).to_numpy(), blobs(batch, "text")
            order = np.argsort(ids, kind="stable")
            ids, texts, found = ids[order], [texts[i] for i in order], []
            for first, _, hashes, _, _, bounds in hashed_runs(texts, hasher):
                h, at, owner, check = text_windows(hashes, bounds, width, checks=True)
                found.append((h, at - bounds[owner], owner + first, check))
            h, at, owner, check = (np.concatenate(x) for x in zip(*found))
            order = np.argsort(h, kind="stable")  # smaller ids come first among equals
            if ((h[order][1:] == h[order][:-1]) & (check[order][1:] != check[order][:-1])).any():
                order = np.lexsort((owner, check, h))
            h, at, owner, check = h[order], at[order], owner[order], check[order]
            bounds = cuts(h, check)
            lead = np.repeat(ids[owner[bounds[:-1]]], np.diff(bounds))
            late = ids[owner] != lead  # an earlier document of this batch has it
            head = np.zeros(len(h), dtype=bool)
            head[bounds[:-1]] = True
            rows = []
            e_hash, e_id, e_check = h[head], ids[owner[head]], check[head]
            bucket = bucket_of(e_check, n)
            by = np.lexsort((e_id, bucket))
            edge = cuts(bucket[by])
            for a, b in zip(edge[:-1], edge[1:]):
                i = by[a:b]
                c = cuts(e_id[i])
                rows.append((int(bucket[i[0]]), 0, pack(e_id[i][c[:-1]], np.diff(c), e_hash[i], e_check[i].astype(np.uint8))))
            if late.any():
                rows.extend(_intervals(owner[late], at[late], ids, width, n))
            yield packed(rows)

    return run


def _texts(n):
    def run(batches):
        for batch in portions(batches, "text"):
            ids, known = batch.column(0).to_numpy(), batch.column(1).to_numpy(zero_copy_only=False)
            own = [blobs(batch, name) for name in batch.schema.names[2:]]
            other = np.array([0 if k else zlib.crc32(t or b"") % n for k, t in zip(known, own[0])], dtype=np.int64)
            part = np.where(known, part_of(ids, n), other)
            by = np.argsort(part, kind="stable")
            edge = cuts(part[by])
            yield packed([(int(part[by[a]]), 2, pack_rows(ids[by[a:b]], known[by[a:b]], [[c[i] for i in by[a:b]] for c in own])) for a, b in zip(edge[:-1], edge[1:])])

    return run


def packed(rows):
    """Rows of (bucket, kind, data) as an Arrow batch."""
    kinds = (pa.int32(), pa.int32(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(c, type=k) for c, k in zip(zip(*rows) if rows else ((), (), ()), kinds)], names=["bucket", "kind", "data"])


def _intervals(owner, at, ids, width, n):
    """Rows of kind 1: word ranges known to go, merged, packed by document part."""
    order = np.lexsort((at, owner))
    owner, at = owner[order], at[order]
    new = np.ones(len(at), dtype=bool)
    new[1:] = (owner[1:] != owner[:-1]) | (at[1:] > at[:-1] + width)
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(at)) - 1
    doc, start, end = ids[owner[first]], at[first], at[last] + width
    part = part_of(doc, n)
    by = np.argsort(part, kind="stable")
    edge = cuts(part[by])
    for a, b in zip(edge[:-1], edge[1:]):
        i = by[a:b]
        yield int(part[i[0]]), 1, pack(doc[i], start[i], end[i])


def _judge(n):
    def run(key, rows):
        give_back()
        out = [(int(key[0]), 1, x) for x in rows.loc[rows["kind"] == 1, "data"]]  # made for this part
        hashes, docs, checks = [], [], []
        for blob in rows.loc[rows["kind"] == 0, "data"]:
            d, c, h, x = unpack(blob, np.int64, np.int64, np.uint64, np.uint8)
            docs.append(np.repeat(d, c))
            hashes.append(h)
            checks.append(x)
        if hashes:
            h, d, x = np.concatenate(hashes), np.concatenate(docs), np.concatenate(checks)
            order = np.lexsort((d, x, h))
            h, d, x = h[order], d[order], x[order]
            bounds = cuts(h, x)
            late = d != np.repeat(d[bounds[:-1]], np.diff(bounds))
            h, d = h[late], d[late]
            part = part_of(d, n)
            by = np.lexsort((d, part))
            edge = cuts(part[by])
            for a, b in zip(edge[:-1], edge[1:]):
                i = by[a:b]
                c = cuts(d[i])
                out.append((int(part[i[0]]), 0, pack(d[i][c[:-1]], np.diff(c), h[i])))
        return pd.DataFrame(out, columns=["part", "kind", "data"])

    return run


def _cut(width, names, carry):
    with_text = "kept_text" in names[5:]

    def run(rows):
        give_back()
        hashes, docs, ranges = [], [], {}
        for kind, blob in zip(rows["kind"], rows["data"]):
            if kind == 1:
                for d, a, b in zip(*(x.tolist() for x in unpack(blob, np.int64, np.int64, np.int64))):
                    ranges.setdefault(d, []).append((a, b))
            elif kind == 0:
                d, c, h = unpack(blob, np.int64, np.int64, np.uint64)
                docs.append(np.repeat(d, c))
                hashes.append(h)
        gone = {}
        if hashes:
            h, d = np.concatenate(hashes), np.concatenate(docs)
            by = np.argsort(d, kind="stable")
            edge = cuts(d[by])
            gone = {int(d[by[a]]): np.sort(h[by[a:b]]) for a, b in zip(edge[:-1], edge[1:])}
        hasher, out, kept = WordHasher(lanes=2), [], [[] for _ in carry]
        for blob in rows.loc[rows["kind"] == 2, "data"]:
            ids, (texts, *others) = unpack_rows(blob, 1 + len(carry))
            for own, column in zip(kept, others):
                own.extend(None if x is None else x.decode("utf-8", "surrogatepass") for x in column)
            for first, data, words, starts, ends, bounds in hashed_runs(texts, hasher):
                for i, (a, b) in enumerate(zip(bounds[:-1], bounds[1:])):
                    doc = ids[first + i]
                    drop = np.zeros(b - a + 1, dtype=np.int64)
                    for x, y in ranges.get(doc, ()):
                        drop[x] += 1
                        drop[y] -= 1
                    if doc in gone:
                        w = text_windows(words[a:b], np.array([0, b - a]), width)[0]
                        known = gone[doc]
                        at = np.searchsorted(known, w)
                        hit = np.flatnonzero(known[np.minimum(at, len(known) - 1)] == w)
                        np.add.at(drop, hit, 1)
                        np.add.at(drop, hit + width, -1)
                    out.append((doc, *_kept(data, starts[a:b], ends[a:b], np.cumsum(drop)[: b - a] > 0, with_text)))
        frame = pd.DataFrame(out, columns=names)
        frame[names[0]] = frame[names[0]].astype("Int64")
        for name, own in zip(carry, kept):
            frame[name] = own
        return frame

    return run


def _kept(data, starts, ends, drop, with_text):
    flags = np.zeros(len(drop) + 2, dtype=np.int8)
    flags[1:-1] = drop
    edge = np.diff(flags)
    gone = list(map(list, zip(np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist())))
    keep, at = [], 0
    for a, b in [*gone, [len(drop), len(drop)]]:
        if a > at:
            keep.extend(data[starts[at] : ends[a - 1]].split())
        at = b
    text = b" ".join(keep)
    row = (len(drop), int(drop.sum()), hashlib.sha256(text).hexdigest(), gone)
    return (*row, text.decode("utf-8", "surrogatepass")) if with_text else row
