"""Exact set-similarity join of documents on word shingles (T-occurrence search).

Two documents link when |x & y| * 100 >= percent * |x | y|. A text's set holds the
hashes of its distinct runs of ``width`` words (A-Z lower-cased).

Plan. (1) Texts become (id, set size, set digest); equal sets are one entity, so
copies cost nothing further. (2) Inverted lists: shingles travel as packed arrays
to hash buckets, where each learns in how many sets it occurs; a shingle of one
set cannot overlap and ends there. (3) Back at its entity, a set whose shared
shingles are fewer than the least overlap T of any link is finished; of the rest,
the n - T + 1 rarest shingles are its short lists: a linked pair meets in one of
them. (4) Linked sets have sizes within the ratio of the threshold, so they lie in the
same or in next size bands; stars around each list's smallest set of two next bands
span candidate groups (connected components, never all pairs of a list). (5) Groups go
to tasks whole if small. A larger group is dealt in cells of a size band and a hash,
and a task holds two cells of the same or of next bands, so no task grows with its
group and no set goes to bands that it cannot link with. In a task DivideSkip runs:
short lists are merged and counted, the longest lists are probed by binary search, and
documents that reach the required overlap link. Documents that are joined already are
skipped, so a group of n copies costs about n links.

Defined results: null, empty or blank text: size 0, linked with nothing; fewer
words than ``width``: the whole word sequence is the one shingle; rows that repeat
a doc_id are separate rows of one component if their sets are equal; a row with a
null id takes part in links, and the smallest non-null id names the component
(null if there is none). Shingles are compared by 64 bits of two Rabin-Karp polynomials;
sets by a digest of 128 bits (one half names a set; if two sets share it, the other does).
"""

from __future__ import annotations

import hashlib
import heapq
from math import ceil, log, log2

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .durable import slices, stored
from .substring import packed
from .wordhash import WordHasher, blobs, bucket_of, cuts, give_back, hashed_runs, pack, portions, spread, text_windows, unpack, windows

BLOCK = 1000
#: Sets of one batch that make a shingle common: its list is then taken as the longest kind everywhere.
COMMON = 8
#: Cost of a probe against that of a merged posting, in the choice of the long lists.
PROBE_COST = 0.0085
_LONG = np.iinfo(np.int64).max


def shingle_sets(texts, width, hasher):
    """For each text: the sorted distinct shingle hashes (uint64) of its words."""
    for _, _, words, _, _, bounds in hashed_runs(texts, hasher):
        h, _, owner = text_windows(words, bounds, width)
        edge = np.searchsorted(owner, np.arange(len(bounds)))
        for i, (a, b) in enumerate(zip(bounds[:-1], bounds[1:])):
            if b - a >= width:
                yield np.unique(h[edge[i] : edge[i + 1]])
            elif b > a:  # a shorter sequence is one shingle, apart from those of full width
                yield windows(words[a:b], int(b - a)) ^ np.uint64(b - a)
            else:
                yield np.zeros(0, dtype=np.uint64)


def digests(values):
    """Two 64-bit digests of a sorted set of hashes."""
    whole = hashlib.blake2b(np.ascontiguousarray(values).tobytes(), digest_size=16).digest()
    return int.from_bytes(whole[:8], "little", signed=True), int.from_bytes(whole[8:], "little", signed=True)


def node_of(values, clashes):
    """Name of a set: its first digest, or the second one where different sets share the first."""
    first, second = digests(values)
    return second if first in clashes else first


def least_overlap(n, percent):
    """Smallest overlap of a set of size n with any set it can link to."""
    return -(-percent * n // 100)


def needed_overlap(n, m, percent):
    """Smallest overlap at which sets of sizes n and m link."""
    return -(-percent * (n + m) // (100 + percent))


def jaccard_components(docs: DataFrame, width: int, percent: int, id_col: str = "doc_id", text_col: str = "text", block: int = BLOCK) -> DataFrame:
    """id, n_shingles, component_id, set_digest for every row of ``docs``."""
    if not 1 <= percent <= 100 or width < 1:
        raise ValueError("percent is 1 to 100 and width at least 1")
    slim = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    n = slices(slim)
    sets = stored(slim.select(F.coalesce("id", F.lit(0)).alias("id"), F.col("id").isNotNull().alias("known"), "text").mapInArrow(_sizes(width), "id long, known boolean, n long, digest long, check long"), "sets")
    # Different sets with one digest: about (distinct sets)**2 / 2**65, so 3 among 10**10.
    shared = sets.where("n > 0").groupBy("digest").agg(F.min("check").alias("a"), F.max("check").alias("b")).where("a != b").select("digest")
    clashes = frozenset(r[0] for r in shared.collect())
    if clashes:
        sets = sets.withColumn("digest", F.when(F.col("digest").isin(*clashes), F.col("check")).otherwise(F.col("digest")))
    lists = slim.select("text").mapInArrow(_entries(width, n, clashes), "bucket int, kind int, data binary")
    shared = lists.groupBy("bucket").applyInPandas(_frequencies(n), "part int, kind int, data binary")
    entities = stored(shared.groupBy("part").applyInPandas(_short_lists(percent), "node long, n long, shared binary, short array<long>"), "short-lists")
    groups = _candidate_groups(entities, percent)
    roots = _linked(entities, groups, percent, block)
    by_set = sets.where("n > 0").groupBy("digest").agg(F.min(F.when(F.col("known"), F.col("id"))).alias("low"))
    by_set = by_set.join(roots.select(F.col("node").alias("digest"), "root"), "digest", "left").withColumn("root", F.coalesce("root", "digest"))
    names = by_set.groupBy("root").agg(F.min("low").alias("component_id"))
    by_set = stored(by_set.join(names, "root").select("digest", "component_id"), "set-components")
    own = F.when(F.col("known"), F.col("id"))
    return sets.join(by_set, "digest", "left").select(
        own.alias(id_col), F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("component_id")).otherwise(own).alias("component_id"), F.col("digest").alias("set_digest")
    )


def _sizes(width):
    def run(batches):
        hasher = WordHasher(lower=True)
        for batch in portions(batches, "text"):
            rows = [(len(s), *(digests(s) if len(s) else (None, None))) for s in shingle_sets(blobs(batch, "text"), width, hasher)]
            found = [pa.array(c, type=pa.int64()) for c in zip(*rows)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *found], names=["id", "known", "n", "digest", "check"])

    return run


def _entries(width, n, clashes=frozenset()):
    """Kind 0: (sets, counts, hashes) of a bucket; 1: common shingles there; 2: what is
    known already at a set's own part (sizes, and its common shingles)."""

    def run(batches):
        hasher = WordHasher(lower=True)
        for batch in portions(batches, "text"):
            found = {}
            for s in shingle_sets(blobs(batch, "text"), width, hasher):
                if len(s):
                    found.setdefault(node_of(s, clashes), s)
            if not found:
                continue
            nodes = np.array(sorted(found), dtype=np.int64)
            sizes = np.array([len(found[d]) for d in nodes.tolist()], dtype=np.int64)
            h, node = np.concatenate([found[d] for d in nodes.tolist()]), np.repeat(nodes, sizes)
            order = np.argsort(h, kind="stable")
            h, node = h[order], node[order]
            bounds = cuts(h)
            often = np.repeat(np.diff(bounds) >= COMMON, np.diff(bounds))
            heads = np.zeros(len(h), dtype=bool)
            heads[bounds[:-1]] = True
            rows = []
            for kind, hh, dd in ((0, h[~often], node[~often]), (1, h[often & heads], node[often & heads])):
                bucket = bucket_of(hh, n)
                edge = cuts(bucket)
                for a, b in zip(edge[:-1], edge[1:]):
                    by = np.argsort(dd[a:b], kind="stable")
                    c = cuts(dd[a:b][by])
                    rows.append((int(bucket[a]), kind, pack(dd[a:b][by][c[:-1]], np.diff(c), hh[a:b][by]) if kind == 0 else pack(hh[a:b])))
            part = spread(nodes, n)
            by = np.argsort(part, kind="stable")
            edge = cuts(part[by])
            rows.extend((int(part[by[a]]), 2, _sized(nodes[by[a:b]], sizes[by[a:b]])) for a, b in zip(edge[:-1], edge[1:]))
            rows.extend((p, 3, blob) for p, blob in _answers(node[often], h[often], np.full(int(often.sum()), _LONG), n))
            yield packed(rows)

    return run


def _sized(nodes, sizes):
    return pack(nodes, sizes)


def _answers(node, h, df, n):
    """(part, blob of (sets, counts, hashes, frequencies)) of rows dealt by set."""
    part = spread(node, n)
    by = np.lexsort((h, node, part))
    edge = cuts(part[by])
    for a, b in zip(edge[:-1], edge[1:]):
        i = by[a:b]
        c = cuts(node[i])
        yield int(part[i[0]]), pack(node[i][c[:-1]], np.diff(c), h[i], df[i])


def _frequencies(n):
    def run(key, rows):
        give_back()
        out = [(int(key[0]), kind, x) for kind, x in zip(rows["kind"], rows["data"]) if kind >= 2]
        hashes, nodes = [], []
        for blob in rows.loc[rows["kind"] == 0, "data"]:
            d, c, h = unpack(blob, np.int64, np.int64, np.uint64)
            nodes.append(np.repeat(d, c))
            hashes.append(h)
        common = [unpack(x, np.uint64)[0] for x in rows.loc[rows["kind"] == 1, "data"]]
        common = np.unique(np.concatenate(common)) if common else np.zeros(0, dtype=np.uint64)
        if hashes:
            h, d = np.concatenate(hashes), np.concatenate(nodes)
            order = np.lexsort((d, h))
            h, d = h[order], d[order]
            fresh = np.ones(len(h), dtype=bool)
            fresh[1:] = (h[1:] != h[:-1]) | (d[1:] != d[:-1])
            h, d = h[fresh], d[fresh]
            bounds = cuts(h)
            df = np.repeat(np.diff(bounds), np.diff(bounds))
            df[np.isin(h, common)] = _LONG
            keep = df > 1
            out.extend((p, 3, blob) for p, blob in _answers(d[keep], h[keep], df[keep], n))
        return pd.DataFrame(out, columns=["part", "kind", "data"])

    return run


def _short_lists(percent):
    def run(key, rows):
        give_back()
        sizes, nodes, hashes, freqs = {}, [], [], []
        for kind, blob in zip(rows["kind"], rows["data"]):
            if kind == 2:
                d, s = unpack(blob, np.int64, np.int64)
                sizes.update(zip(d.tolist(), s.tolist()))
            else:
                d, c, h, f = unpack(blob, np.int64, np.int64, np.uint64, np.int64)
                nodes.append(np.repeat(d, c))
                hashes.append(h)
                freqs.append(f)
        out = []
        if nodes:
            d, h, f = np.concatenate(nodes), np.concatenate(hashes), np.concatenate(freqs)
            order = np.lexsort((h, f, d))  # rarest first within a set; ties by hash, alike everywhere
            d, h, f = d[order], h[order], f[order]
            edge = cuts(d)
            for a, b in zip(edge[:-1], edge[1:]):
                own = np.unique(h[a:b])  # a common shingle comes once from each batch with the set
                n, t = sizes[int(d[a])], least_overlap(sizes[int(d[a])], percent)
                if len(own) < t:
                    continue
                short = n - t + 1 - (n - len(own))
                ranked = h[a:b][np.sort(np.unique(h[a:b], return_index=True)[1])]
                out.append((int(d[a]), n, own.tobytes(), ranked[:short].view(np.int64)))
        return pd.DataFrame(out, columns=["node", "n", "shared", "short"])

    return run


def _band(percent):
    """Size band: sizes of a linked pair lie in the same or in next bands."""
    if percent == 100:
        return F.col("n").cast("int")
    return F.floor(F.log(F.col("n").cast("double")) / F.lit(-log(percent / 100) * (1 + 1e-6))).cast("int")


def _candidate_groups(entities, percent):
    """(node, root) of sets that meet in a short list and whose bands are the same or next, as
    stars around the smallest set of each list in two next bands."""
    both = F.array(_band(percent), _band(percent) + 1)
    met = entities.select("node", F.explode("short").alias("token"), both.alias("bands")).select("node", "token", F.explode("bands").alias("upto"))
    lists = met.groupBy("token", "upto").agg(F.min("node").alias("low"), F.max("node").alias("high")).where("low != high").select("token", "upto", "low")
    return connected_components(met.join(lists, ["token", "upto"]).where("node != low").select(F.col("node").alias("a"), F.col("low").alias("b")))


def _linked(entities, groups, percent, block):
    """(node, root) of linked sets: tasks of whole groups or of two cells, then the components of their links."""
    here = stored(groups.join(entities, "node").withColumn("band", _band(percent)), "groups")
    total = here.count()
    bundles = max(1, ceil(4 * total / block))  # several whole groups a task
    sizes = here.groupBy("root").agg(F.count("*").alias("size"))
    large = sizes.where(F.col("size") > block).select("root")
    small = here.join(large, "root", "left_anti").select(F.pmod(F.xxhash64("root"), F.lit(bundles)).alias("task"), F.lit(0).alias("cell"), F.lit(0).alias("other"), "node", "n", "shared")
    # Cells of a large group: by band, and by a hash into cells of half a block.
    cells = here.join(large, "root").groupBy("root", "band").agg(F.ceil(2 * F.count("*") / block).cast("int").alias("k"))
    near = cells.select("root", F.explode(F.array(F.col("band") - 1, F.col("band"), F.col("band") + 1)).alias("band"), F.col("band").alias("to"), F.col("k").alias("to_k"))
    cut = here.join(cells, ["root", "band"]).withColumn("cell", F.pmod(F.xxhash64("node"), F.col("k")).cast("int")).join(near, ["root", "band"])
    cut = cut.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("to_k") - 1)))
    own, to = F.struct(F.col("band").alias("b"), F.col("cell").alias("c")), F.struct(F.col("to").alias("b"), F.col("other").alias("c"))
    task = F.xxhash64("root", F.least(own, to), F.greatest(own, to))
    # A cell alone is compared in itself only where it meets itself.
    cut = cut.select(task.alias("task"), F.when(own == to, 0).when(own < to, 1).otherwise(2).alias("cell"), F.lit(1).alias("other"), "node", "n", "shared")
    links = small.unionByName(cut).groupBy("task").applyInPandas(_divide_skip(percent), "a long, b long, k int")
    links = stored(links, "links")
    whole = links.where("k = 0").select(F.col("a").alias("node"), F.col("b").alias("root"))
    if links.where("k = 1").isEmpty():
        return whole
    return whole.unionAll(connected_components(links.where("k = 1").select("a", "b")))


def _divide_skip(percent):
    def run(rows):
        give_back()
        side = rows["cell"].to_numpy(np.int64)
        found = link_all(rows["node"].to_numpy(np.int64), rows["n"].to_numpy(np.int64), [np.frombuffer(x, dtype=np.uint64) for x in rows["shared"]], percent, side if side.any() else None)
        split = int(rows["other"].iloc[0])
        return pd.DataFrame([(a, b, split) for a, b in found], columns=["a", "b", "k"]).astype({"a": "int64", "b": "int64", "k": "int32"})

    return run


def link_all(nodes, sizes, sets, percent, side=None):
    """(node, smallest node of its component) under the links among these sets; with ``side``
    (1 or 2), under the links between the sides."""
    order = np.lexsort((nodes, sizes))
    root = np.arange(len(nodes))

    def find(i):
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    tokens, codes = np.unique(np.concatenate(sets) if sets else np.zeros(0, np.uint64), return_inverse=True)
    edge = np.zeros(len(sets) + 1, dtype=np.int64)
    edge[1:] = np.cumsum([len(s) for s in sets])
    lengths = np.bincount(codes, minlength=len(tokens))
    at = np.zeros(len(tokens) + 1, dtype=np.int64)
    at[1:] = np.cumsum(lengths)
    postings, filled = np.empty(len(codes), dtype=np.int32), np.zeros(len(tokens), dtype=np.int64)
    for place, i in enumerate(order):
        own = codes[edge[i] : edge[i + 1]]
        n = int(sizes[i])
        least = needed_overlap(n, least_overlap(n, percent), percent)
        if least <= len(own):
            own = own[np.lexsort((own, filled[own]))]
            skip = long_lists(least, int(filled[own[-1]]), len(own))
            for other in _reach(own, skip, least, postings, at, filled):
                j = int(order[other])
                if (side is not None and side[i] == side[j]) or find(i) == find(j):
                    continue
                need = needed_overlap(n, int(sizes[j]), percent)
                if need <= min(len(own), edge[j + 1] - edge[j]) and _overlap(own, other, postings, at, filled, need):
                    a, b = find(i), find(j)
                    root[max(a, b, key=lambda x: nodes[x])] = min(a, b, key=lambda x: nodes[x])
            own = codes[edge[i] : edge[i + 1]]
        postings[at[own] + filled[own]] = place  # lists stay sorted by place
        filled[own] += 1
    return [(int(nodes[i]), int(nodes[find(i)])) for i in range(len(nodes))]


def long_lists(least, longest, lists):
    """How many of the longest lists are only probed: fewer as they grow, ``least`` - 1 at most."""
    return min(least - 1, lists - 1, int(least / (PROBE_COST * log2(max(longest, 1) + 1) + 1)))


def _reach(own, skip, least, postings, at, filled):
    """Merge the short lists; candidates with enough occurrences there, most first."""
    short = own[: len(own) - skip]
    runs = [postings[at[t] : at[t] + filled[t]] for t in short if filled[t]]
    if not runs:
        return []
    heapq.heapify(runs := [(len(r), i, r) for i, r in enumerate(runs)])
    while len(runs) > 1:  # the two shortest runs merge first
        (_, i, a), (_, _, b) = heapq.heappop(runs), heapq.heappop(runs)
        both = np.concatenate([a, b])
        both.sort(kind="stable")  # merges sorted runs
        heapq.heappush(runs, (len(both), i, both))
    merged = runs[0][2]
    edge = cuts(merged)
    count = np.diff(edge)
    enough = count >= least - skip
    found, count = merged[edge[:-1]][enough], count[enough]
    return found[np.argsort(-count, kind="stable")].tolist()


def _overlap(own, other, postings, at, filled, need):
    """Whether ``other`` is in ``need`` of the lists, by binary search; stops when it cannot be."""
    have, left = 0, len(own)
    for t in own:
        a, n = at[t], filled[t]
        if n:
            p = a + np.searchsorted(postings[a : a + n], other)
            have += p < a + n and postings[p] == other
        left -= 1
        if have >= need:
            return True
        if have + left < need:
            return False
    return False
