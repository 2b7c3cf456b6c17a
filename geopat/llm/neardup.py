"""Near duplicates by bottom-k sketches from one hash function.

A document's set holds the hashes of its n-word shingles (of all its words, where it has fewer), words
lower-cased for A-Z.  Its sketch is the k smallest.  Documents with equal sets are one
class and stand for one another.  Inverted lists hold, for each run of three retained values
that follow one another in a sketch, the classes that retain it.  Sets that reach the
threshold 0.8 always share such a run when their sketches are whole (a difference of at
most a quarter of the shared values cannot cut them all; sets of four and five also
list runs of two), and fail to with a chance under 1e-9 when cut at 64.  Runs, unlike
single values, are rare among documents that merely share common words: a single value of a
common shingle has a list as long as the corpus.

Short lists give all their pairs of fitting sizes.  Of long lists each member is paired with the
pivot (a list's smallest id) that shares most lists with it, first within each task's sketches, so that only the task's pivot of such a list goes on
to the list of the whole.  Members whose component then differs from that of a pivot they were listed with
are compared in blocks inside tasks, with all that their cluster lists, and only links come out.
Every candidate passes the estimate from the sketch of the union (a filter five standard errors
wide) and then exact comparison of full sets.  No list is cut and no partner dropped.

Null and empty texts and texts without words have empty sets and link with nothing.
Rows with a null id link with nothing, have no component and are kept.  Rows that
share an id count as one node; each must match what another row links with.  Other
columns are not read.  An empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geopat.plans.components import connected, forest
from geopat.plans.scratch import hot_join

from .common import materialise, parts_for, ship, table
from .wordhash import Words, blocks, gram_hash, mix, window_mask

K = 64
RUN = 3
#: Lists up to this length give all pairs.
SHORT = 24
#: Members that a list must have among one task's sketches to be reduced to its pivots there.
LOCAL = 8
#: Mark, beside a set's size, of an entry that stands for such a list.
PIVOT = np.uint32(1 << 31)
#: Classes whose sketches are listed together.
GATHER = 20_000
#: List entries of a part.
PART = 800_000
BLOCK = 512
#: Values that the sets of one side of a block may have in all.
BLOCK_VALUES = 400_000
#: Shared values counted at a time.
WIDTH = 4096
#: Pairs whose sketches estimate a similarity this far below the threshold are not verified.
SLACK = 0.25


def shingles(texts: list[bytes], words: int) -> tuple[np.ndarray, np.ndarray]:
    """(edges, hashes): the distinct shingle hashes of text i, ascending, are hashes[edges[i]:edges[i+1]]."""
    w = Words(texts, lower=True)
    h = gram_hash(w.hash, words)
    inside = window_mask(w.first, words, len(w.hash))
    owner = w.owner()
    o = owner[: len(h)][inside]
    h = h[inside]
    at = np.searchsorted(o, np.arange(len(texts) + 1)).tolist()
    for a, b in zip(at[:-1], at[1:], strict=True):  # a short sort for each text costs less than one of the block by text and hash
        h[a:b].sort()
    n = np.diff(w.first)
    short = np.flatnonzero((n > 0) & (n < words))
    if len(short):
        whole = [mix(gram_hash(w.hash[w.first[i] : w.first[i + 1]], int(n[i])) + np.uint64(n[i])) for i in short]
        h, o = np.concatenate((h, *whole)), np.concatenate((o, short))
        order = np.argsort(o, kind="stable")
        h, o = h[order], o[order]
    fresh = np.ones(len(h), bool)
    fresh[1:] = (h[1:] != h[:-1]) | (o[1:] != o[:-1])
    h, o = h[fresh], o[fresh]
    return np.searchsorted(o, np.arange(len(texts) + 1)), h


def _fold(h: np.ndarray, edges: np.ndarray) -> np.ndarray:
    total = np.concatenate((np.zeros(1, np.uint64), np.cumsum(h, dtype=np.uint64)))
    return (total[edges[1:]] - total[edges[:-1]]).view(np.int64)


def sketches(docs: DataFrame, words: int, k: int = K) -> DataFrame:
    """doc_id, n (set size), d1 and d2 (digest of the set), sketch (its k smallest hashes)."""

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in rows:
            for first, block in blocks(batch["text"].to_pylist()):
                edges, h = shingles(block, words)
                low = [h[a : min(a + k, b)].tobytes() for a, b in zip(edges[:-1], edges[1:], strict=True)]
                yield pa.RecordBatch.from_arrays(
                    [batch["doc_id"].slice(first, len(block)), pa.array(np.diff(edges)), pa.array(_fold(h, edges)), pa.array(_fold(mix(h ^ np.uint64(0xABCDEF)), edges)), pa.array(low, pa.binary())],
                    names=["doc_id", "n", "d1", "d2", "sketch"],
                )

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, n long, d1 long, d2 long, sketch binary")


def _runs(values: np.ndarray) -> np.ndarray:
    if not len(values):
        return np.zeros(1, np.int64)
    return np.append(np.flatnonzero(np.concatenate(([True], values[1:] != values[:-1]))), len(values))


def _fits(x: np.ndarray, y: np.ndarray, percent: int) -> np.ndarray:
    return 100 * np.minimum(x, y) >= percent * np.maximum(x, y)


def _stars(ids: np.ndarray, sizes: np.ndarray, edges: np.ndarray, chosen: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Of lists (ids ascending in edges[i]:edges[i+1]): for each member a candidate pair with the pivot that shares most lists with it, and all (pivot, member).

    A list's pivot is its smallest id.  Of equally shared pivots the smallest counts; pairs of sizes that do not fit are left out.
    """
    none = np.zeros((0, 2), np.int64)
    if not len(chosen):
        return none, none
    length = np.diff(edges)[chosen]
    at = np.repeat(edges[chosen], length) + np.arange(length.sum()) - np.repeat(np.cumsum(length) - length, length)
    first = np.repeat(edges[chosen], length)
    fits = _fits(sizes[at], sizes[first], percent)
    rows, where, shared = np.unique(np.column_stack((ids[at], ids[first])), axis=0, return_inverse=True, return_counts=True)
    fit = np.zeros(len(rows), bool)
    np.logical_or.at(fit, where.ravel(), fits)
    apart = rows[:, 0] != rows[:, 1]
    rows, shared, fit = rows[apart], shared[apart], fit[apart]
    order = np.lexsort((rows[:, 1], -shared, rows[:, 0]))
    order = order[fit[order]]
    best = order[np.flatnonzero(np.concatenate(([True], rows[order[1:], 0] != rows[order[:-1], 0])))] if len(order) else order
    return rows[best][:, ::-1], rows[:, ::-1]


_LISTED = "part int, keys binary, ids binary, sizes binary"


def _packed(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int32(), pa.binary(), pa.binary(), pa.binary())
    columns = zip(*rows, strict=True) if rows else [[] for _ in kinds]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=["part", "keys", "ids", "sizes"])


def list_entries(classes: DataFrame, parts: int, percent: int) -> DataFrame:
    """Packed rows: entries of inverted lists, dealt by key; under part -1 candidate pairs and under -2 (pivot, member), both from lists that are long within a task."""

    def entries(ids: np.ndarray, n: np.ndarray, raw: list[np.ndarray]) -> pa.RecordBatch:
        first = np.concatenate(([0], np.cumsum([len(x) for x in raw])))
        flat = np.concatenate(raw)
        owner = np.repeat(np.arange(len(raw)), np.diff(first))
        keys, owners = [], []
        for length in (RUN, 2):
            h = gram_hash(flat, length)
            inside = window_mask(first, length, len(flat))
            at = owner[: len(h)]
            if length == 2 and len(h):
                inside &= n[at] <= 5
            keys.append(mix(h[inside] + np.uint64(length)))
            owners.append(at[inside])
        keys, owners = np.concatenate(keys), np.concatenate(owners)
        order = np.lexsort((ids[owners], keys))
        keys, owners = keys[order], owners[order]
        edges = _runs(keys)
        length = np.diff(edges)
        long = np.flatnonzero(length >= LOCAL)
        pairs, members = _stars(ids[owners], n[owners], edges, long, percent)
        stays = np.repeat(length < LOCAL, length)
        stays[edges[long]] = True
        size = n[owners].astype(np.uint32)
        size[edges[long]] |= PIVOT
        keys, owners, size = keys[stays], owners[stays], size[stays]
        part = (keys % np.uint64(parts)).astype(np.int32)
        order = np.argsort(part, kind="stable")
        part, keys, owners, size = part[order], keys[order], owners[order], size[order]
        edges = _runs(part)
        out = [(int(part[a]), keys[a:b].tobytes(), ids[owners[a:b]].tobytes(), size[a:b].tobytes()) for a, b in zip(edges[:-1], edges[1:], strict=True) if b > a]
        out += [(kind, x[:, 0].tobytes(), x[:, 1].tobytes(), b"") for kind, x in ((-1, pairs), (-2, members)) if len(x)]
        return _packed(out)

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, n, raw = [], [], []
        for batch in rows:
            ids.append(batch["doc_id"].to_numpy())
            n.append(batch["n"].to_numpy())
            raw += [np.frombuffer(x, np.uint64) for x in batch["sketch"].to_pylist()]
            if len(raw) >= GATHER:
                yield entries(np.concatenate(ids), np.concatenate(n), raw)
                ids, n, raw = [], [], []
        if raw:
            yield entries(np.concatenate(ids), np.concatenate(n), raw)

    return classes.select("doc_id", "n", "sketch").mapInArrow(run, _LISTED)


def list_pairs(listed: DataFrame, percent: int) -> DataFrame:
    """The same packed rows, -1 and -2, from the lists of the whole."""

    def run(rows: pa.Table) -> pa.Table:
        keys = np.concatenate([np.frombuffer(x, np.uint64) for x in rows["keys"].to_pylist()])
        ids = np.concatenate([np.frombuffer(x, np.int64) for x in rows["ids"].to_pylist()])
        n = np.concatenate([np.frombuffer(x, np.uint32) for x in rows["sizes"].to_pylist()])
        order = np.lexsort((ids, keys))
        keys, ids, n = keys[order], ids[order], n[order]
        pivot, n = (n & PIVOT) > 0, (n & ~PIVOT).astype(np.int64)
        edges = _runs(keys)
        length = np.diff(edges)
        pairs = [np.zeros((0, 2), np.int64)]
        # Short lists: every place with the place d further on, for each d.
        of = np.repeat(np.arange(len(length)), length)
        short = (length <= SHORT)[of] if len(of) else np.zeros(0, bool)
        for d in range(1, min(SHORT, int(length.max(initial=0)))):
            here = np.flatnonzero(short[:-d] & (of[:-d] == of[d:]))
            here = here[_fits(n[here], n[here + d], percent) & (ids[here] != ids[here + d])]
            pairs.append(np.column_stack((ids[here], ids[here + d])))
        # A short list that holds the pivot of a task's long one stands for more members than it lists.
        stands = np.bincount(of[pivot], minlength=len(length)) > 0
        chain = np.flatnonzero(short[:-1] & (of[:-1] == of[1:]) & stands[of[:-1]])
        starred, members = _stars(ids, n, edges, np.flatnonzero(length > SHORT), percent)
        pairs = np.unique(np.concatenate((*pairs, starred)), axis=0)
        members = np.unique(np.concatenate((members, np.column_stack((ids[edges[of[chain]]], ids[chain + 1])))), axis=0)
        out = [(kind, x[:, 0].tobytes(), x[:, 1].tobytes(), b"") for kind, x in ((-1, pairs), (-2, members)) if len(x)]
        return pa.Table.from_batches([_packed(out)])

    return listed.where("part >= 0").groupBy("part").applyInArrow(run, _LISTED)


def _unpacked(rows: DataFrame, kind: int) -> DataFrame:
    """Distinct (a, b) of the packed rows of one kind."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [np.zeros((0, 2), np.int64)]
        for batch in batches:
            held += [np.column_stack((np.frombuffer(a, np.int64), np.frombuffer(b, np.int64))) for a, b in zip(batch["keys"].to_pylist(), batch["ids"].to_pylist(), strict=True)]
            if sum(map(len, held)) > PART:
                x = np.unique(np.concatenate(held), axis=0)
                yield pa.RecordBatch.from_arrays([pa.array(x[:, 0]), pa.array(x[:, 1])], names=["a", "b"])
                held = [np.zeros((0, 2), np.int64)]
        x = np.unique(np.concatenate(held), axis=0)
        yield pa.RecordBatch.from_arrays([pa.array(x[:, 0]), pa.array(x[:, 1])], names=["a", "b"])

    return rows.where(F.col("part") == kind).select("keys", "ids").mapInArrow(run, "a long, b long").where("a <> b").distinct()


def estimate(x: np.ndarray, y: np.ndarray, k: int) -> float:
    """Similarity from two sketches: shared values among the k smallest of their union."""
    both = np.sort(np.concatenate((x, y)))
    twin = np.zeros(len(both), bool)
    twin[1:] = both[1:] == both[:-1]
    kept = ~twin
    rank = np.cumsum(kept)
    m = min(k, int(rank[-1])) if len(both) else 0
    return float((twin & (rank <= m)).sum()) / m if m else 0.0


def estimated(pairs: DataFrame, sketch: DataFrame, k: int, percent: int) -> DataFrame:
    """The pairs (a, b) that sketches do not rule out."""
    left = sketch.select(F.col("doc_id").alias("a"), F.col("sketch").alias("sa"))
    right = sketch.select(F.col("doc_id").alias("b"), F.col("sketch").alias("sb"))

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in rows:
            good = [
                estimate(np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64), k) >= percent / 100 - SLACK
                for x, y in zip(batch["sa"].to_pylist(), batch["sb"].to_pylist(), strict=True)
            ]
            yield batch.select(["a", "b"]).filter(pa.array(good, pa.bool_()))

    return pairs.join(left, "a").join(right, "b").select("a", "b", "sa", "sb").mapInArrow(run, "a long, b long")


def full_sets(docs: DataFrame, wanted: DataFrame, words: int) -> DataFrame:
    """(doc_id, set) of the documents whose ids are wanted."""

    def sets(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in rows:
            for first, block in blocks(batch["text"].to_pylist()):
                edges, h = shingles(block, words)
                yield pa.RecordBatch.from_arrays([batch["doc_id"].slice(first, len(block)), pa.array([h[a:b].tobytes() for a, b in zip(edges[:-1], edges[1:], strict=True)], pa.binary())], names=["doc_id", "set"])

    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(wanted.distinct().hint("merge"), "doc_id", "left_semi")
    return texts.mapInArrow(sets, "doc_id long, set binary")


def _linked(x: np.ndarray, y: np.ndarray, percent: int) -> bool:
    at = np.minimum(np.searchsorted(x, y), max(len(x) - 1, 0))
    shared = int((x[at] == y).sum()) if len(x) else 0
    return 100 * shared >= percent * (len(x) + len(y) - shared)


def verified(pairs: DataFrame, full: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose full sets reach the threshold."""

    def compare(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in rows:
            good = [
                _linked(np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64), percent)
                for x, y in zip(batch["xa"], batch["xb"], strict=True)
            ]
            yield batch.select(["a", "b"]).filter(pa.array(good, pa.bool_()))

    left = full.select(F.col("doc_id").alias("a"), F.col("set").alias("xa"))
    right = full.select(F.col("doc_id").alias("b"), F.col("set").alias("xb"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", "xa", "xb").mapInArrow(compare, "a long, b long")


def rest_links(members: DataFrame, found: DataFrame, sketch: DataFrame, full: DataFrame, percent: int, k: int) -> DataFrame:
    """Links (a, b) between members of long lists that lie in different components so far.

    Components are a cluster when (pivot, member) rows lead from one to the other.  Within it, sizes fall into bands, each
    wider by the threshold's inverse, so that only neighbouring bands can link.  Members
    go to one block of their band; those outside the cluster's largest component, which
    may link with any member, are dealt against all blocks of the bands around theirs.
    A task compares the sketches of a block, and packs the pairs that may link in one
    row; a second task gets each full set of these once and returns its links alone, thinned to stars.
    """
    of = lambda name: found.select(F.col("node").alias(name), F.col("component").alias(f"c{name}"))
    placed = members.join(of("a"), "a", "left").join(of("b"), "b", "left").select("a", "b", F.coalesce("ca", "a").alias("ca"), F.coalesce("cb", "b").alias("cb"))
    placed = materialise(placed)
    across = materialise(placed.where("ca <> cb").select(F.col("ca").alias("a"), F.col("cb").alias("b")).distinct())
    if across.isEmpty():
        return members.where("false")
    cluster = connected(across).select(F.col("node").alias("component"), F.col("component").alias("cluster"))
    listed = placed.select("a", F.col("ca").alias("component")).union(placed.select("b", "cb")).distinct()
    step = F.floor(F.log("n") / F.log(F.lit(100.0 / percent))).cast("int")
    sized = sketch.select(F.col("doc_id").alias("a"), step.alias("band"))
    parts = materialise(listed.join(cluster, "component").join(sized, "a"))
    big = parts.groupBy("cluster", "component").agg(F.count("*").alias("n")).groupBy("cluster").agg(F.max_by("component", F.struct("n", "component")).alias("big"))
    known = materialise(parts.join(big, "cluster").withColumn("minor", F.col("component") != F.col("big")))
    right = known.select("cluster", "band", "a", "component", "minor", F.lit(False).alias("first"))
    left = known.where("minor").select("cluster", F.explode(F.array(F.col("band") - 1, F.col("band"), F.col("band") + 1)).alias("band"), "a", "component", "minor", F.lit(True).alias("first"))
    both = right.union(left)
    room = F.greatest(F.lit(8), F.least(F.lit(BLOCK), F.floor(BLOCK_VALUES / F.pow(F.lit(100.0 / percent), F.col("band") + 1))))
    count = lambda c: F.ceil(F.sum(c.cast("int")) / F.first(room)).cast("int")
    shape = both.groupBy("cluster", "band").agg(count(F.col("first")).alias("lefts"), count(~F.col("first")).alias("rights")).where("lefts > 0 and rights > 0")
    own, other = F.when(F.col("first"), F.col("lefts")).otherwise(F.col("rights")), F.when(F.col("first"), F.col("rights")).otherwise(F.col("lefts"))
    spread = (
        both.join(shape, ["cluster", "band"])
        .withColumn("own", F.pmod(F.xxhash64("a"), own).cast("int"))
        .withColumn("other", F.explode(F.sequence(F.lit(0), other - 1)))
        .withColumns({"i": F.when(F.col("first"), F.col("own")).otherwise(F.col("other")), "j": F.when(F.col("first"), F.col("other")).otherwise(F.col("own"))})
    )
    slim = spread.select("cluster", "band", "i", "j", "first", "minor", "component", "a").join(sketch.select(F.col("doc_id").alias("a"), "n", "sketch"), "a")

    def compare(group: pa.Table) -> pa.Table:
        first = group["first"].to_numpy(zero_copy_only=False)
        ids, comp, minor, n = (group[c].to_numpy(zero_copy_only=False) for c in ("a", "component", "minor", "n"))
        left, right = np.flatnonzero(first), np.flatnonzero(~first)
        raw = [np.frombuffer(x, np.uint64) for x in group["sketch"].to_pylist()]
        shared = _shared([raw[i] for i in left], [raw[i] for i in right])
        held = np.array([min(len(x), k) for x in raw])
        union = np.minimum(k, held[left][:, None] + held[right][None, :] - shared)
        size = n[left][:, None].astype(np.float64), n[right][None, :].astype(np.float64)
        good = (shared >= (percent / 100 - SLACK) * union) & (100 * np.minimum(*size) >= percent * np.maximum(*size))
        good &= (comp[left][:, None] != comp[right][None, :]) & (~minor[right][None, :] | (ids[left][:, None] < ids[right][None, :]))
        x, y = np.nonzero(good)
        a, b = ids[left[x]], ids[right[y]]
        key = [group[c][0].as_py() for c in ("cluster", "band", "i", "j")] if len(a) else None
        rows = [(*key, a.tobytes(), b.tobytes(), np.union1d(a, b).tolist())] if key else []
        kinds = (pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.list_(pa.int64()))
        columns = zip(*rows, strict=True) if rows else [[] for _ in kinds]
        return pa.table([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=["cluster", "band", "i", "j", "a", "b", "docs"])

    near = materialise(slim.groupBy("cluster", "band", "i", "j").applyInArrow(compare, "cluster long, band int, i int, j int, a binary, b binary, docs array<long>"))
    wanted = near.select(F.col("cluster").alias("c"), F.col("band").alias("d"), F.col("i").alias("x"), F.col("j").alias("y"), F.explode("docs").alias("doc_id"))

    def verify(group: pa.Table, held: pa.Table) -> pa.Table:
        ids = held["doc_id"].to_numpy()
        sets = dict(zip(ids.tolist(), (np.frombuffer(x.as_buffer(), np.uint64) for x in held["set"]), strict=True))
        out_a, out_b = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for raw_a, raw_b in zip(group["a"].to_pylist(), group["b"].to_pylist(), strict=True):
            a, b = np.frombuffer(raw_a, np.int64), np.frombuffer(raw_b, np.int64)
            left, x = np.unique(a, return_inverse=True)
            right, y = np.unique(b, return_inverse=True)
            one, two = [sets[i] for i in left.tolist()], [sets[i] for i in right.tolist()]
            shared = _shared(one, two)[x, y].astype(np.float64)
            total = np.array([len(s) for s in one])[x] + np.array([len(s) for s in two])[y] - shared
            good = 100.0 * shared >= percent * total
            out_a.append(a[good])
            out_b.append(b[good])
        hi, lo = forest(np.concatenate(out_a), np.concatenate(out_b))
        return pa.table([pa.array(hi), pa.array(lo)], names=["a", "b"])

    sets = wanted.join(full, "doc_id")
    return near.groupBy("cluster", "band", "i", "j").cogroup(sets.groupBy("c", "d", "x", "y")).applyInArrow(verify, "a long, b long")


def _shared(left: list[np.ndarray], right: list[np.ndarray]) -> np.ndarray:
    """Numbers of values that each left set shares with each right set."""
    values, row, at = _in_common([*left, *right])
    out = np.zeros((len(left), len(right)), np.float32)
    for low in range(0, values, WIDTH):
        a, b = np.searchsorted(at, (low, low + WIDTH))
        m = np.zeros((len(left) + len(right), WIDTH), np.float32)
        m[row[a:b], at[a:b] - low] = 1
        out += m[: len(left)] @ m[len(left) :].T
    return out


def _in_common(raw: list[np.ndarray]) -> tuple[int, np.ndarray, np.ndarray]:
    """Of sets: how many values are in two or more, and (set, number of such a value), ordered by number."""
    flat = np.concatenate(raw) if raw else np.zeros(0, np.uint64)
    row = np.repeat(np.arange(len(raw), dtype=np.int32), [len(x) for x in raw])
    order = np.argsort(flat, kind="stable")
    flat, row = flat[order], row[order]
    edges = _runs(flat)
    length = np.diff(edges)
    number = np.cumsum(length >= 2, dtype=np.int32) - 1
    keep = np.repeat(length >= 2, length)
    return int((length >= 2).sum()), row[keep], np.repeat(number, length)[keep]


def near_duplicates(docs: DataFrame, words: int = 5, percent: int = 80, k: int = K) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of every row of `docs`."""
    ship(docs.sparkSession)
    sketch = materialise(sketches(docs, words, k))
    known = sketch.where("n > 0 and doc_id is not null")
    groups = known.groupBy("n", "d1", "d2").agg(F.min("doc_id").alias("rep"), F.count("*").alias("copies"))
    # An id with several rows joins the classes of all of them.
    same_id = known.groupBy("doc_id").agg(F.min(F.struct("n", "d1", "d2")).alias("x"), F.max(F.struct("n", "d1", "d2")).alias("y")).where("x <> y")
    doubles = known.join(same_id.select("doc_id"), "doc_id", "left_semi").join(groups, ["n", "d1", "d2"]).select(F.col("doc_id").alias("a"), F.col("rep").alias("b"))
    reps = groups.select(F.col("rep").alias("doc_id"), "n", "d1", "d2")
    classes = materialise(known.join(reps, ["doc_id", "n", "d1", "d2"], "left_semi").dropDuplicates(["doc_id", "n", "d1", "d2"]))
    total = classes.agg(F.sum(F.least("n", F.lit(k)))).first()[0] or 0
    dealt = materialise(list_entries(classes, parts_for(total, PART), percent))
    listed = materialise(dealt.where("part < 0").unionByName(list_pairs(dealt, percent)))
    single = classes.groupBy("doc_id").agg(F.first("n").alias("n"), F.min("sketch").alias("sketch")) if not same_id.isEmpty() else classes.select("doc_id", "n", "sketch")
    pairs = materialise(estimated(_unpacked(listed, -1), single, k, percent))
    members = materialise(_unpacked(listed, -2))
    full = materialise(full_sets(docs, pairs.select(F.col("a").alias("doc_id")).union(pairs.select("b")).union(members.select("a")).union(members.select("b")), words))
    found = connected(materialise(verified(pairs, full, percent).union(doubles)))
    more = materialise(rest_links(members, found, single, full, percent, k))
    if not more.isEmpty():
        found = connected(found.select(F.col("node").alias("a"), F.col("component").alias("b")).union(more))
    labelled = groups.join(found, F.col("rep") == F.col("node"), "left").select("d1", F.col("n").alias("m"), F.col("d2").alias("e2"), F.coalesce("component", "rep").alias("component"), "copies")
    worded = hot_join(known.select("doc_id", "n", "d1", "d2"), materialise(labelled), "d1", "copies", known.count()).where("d2 = e2 and n = m").select("doc_id", "n", "component")
    rest = sketch.where("n = 0 or doc_id is null").select("doc_id", "n", F.col("doc_id").alias("component"))
    return (
        worded.unionByName(rest)
        .select("doc_id", F.col("n").alias("n_shingles"), F.col("component").alias("component_id"))
        .withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))
    )


def keep_one(docs: DataFrame, words: int = 5, percent: int = 80) -> DataFrame:
    """One document of each group of near duplicates, that of the smallest id; columns as in `docs`.

    Rows that share an id stay or go together; rows of null id or without words stay.  An empty table gives no rows.
    """
    gone = near_duplicates(docs, words, percent).where("not kept").select(F.col("doc_id").alias("id")).distinct()
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col("doc_id").cast("long").alias("id"))
    return packed.join(gone, "id", "left_anti").select("row.*")


def op4_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"), words=2)
