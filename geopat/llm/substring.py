"""Removal of repeated passages with prefix-partitioned suffix trees.

Every word of a text starts a suffix, read to the depth of a window (13 words).  A suffix is
filed under its anchor: the suffix from that of its first ten words on whose next four
words hash lowest.  Equal windows have equal anchors, and neighbouring windows mostly share one, so a
segment of words under one anchor carries some five suffixes at once, and words travel about three times
instead of 13 times.  Anchors are grouped by variable-length prefixes: one word, or, while a
prefix has more suffixes than a group should hold, two, three, four.  Groups are packed into parts whose number
follows from the count of suffixes, so a part's size does not depend on the input's.

A part orders its suffixes by their words, four at a time, going on only where suffixes still
agree; where two neighbours part is their common-prefix length.  Neighbours that agree to the
depth of a window are leaves of one deep internal node, a repeat.  A leaf with
another leaf of a smaller document id below its node tells its document to drop those words;
adjoining repeats of a document join into maximal ones.

Before suffixes are dealt, a task orders those it gathered (BATCH) by fingerprint: of equal ones only the
smallest document's goes on, the others are repeats already.  So a passage that any number of documents
hold has one leaf a batch, and no group of copies lands in one task.  No row is left out.

Words are compared by 16 bits of their hash and windows by 16 bits of their fingerprint besides, so 13 words agree by chance with 1 in 2 ** 32 where
they differ in one word.  Null and empty texts have no words.  Rows with a null id neither lose words nor take
them from others.  Rows that share an id are judged each by its own words and never against each other;
repeated rows fare alike.  Other columns are not read, and may have any name.  An empty table gives no rows.
"""

from __future__ import annotations

import heapq
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import parts_for, ship, table
from .wordhash import Words, blocks, gram_hash, window_mask

WINDOW = 13
#: Words of an anchor, the longest prefix that groups are cut by.
ANCHOR = 4
#: Suffixes gathered before a task deals them out.
BATCH = 250_000
#: Suffixes of a part.
PART = 1_000_000
#: Words of segments that go out in one record batch.
SENT = 500_000
#: Parts that the driver's table of prefixes tells apart; a part beyond is cut by the anchor's hash.
MOST_PLANNED = 4096


class Batch:
    """Suffixes of some documents: where they start, whose they are, their anchors and the hashes of these anchors' prefixes."""

    def __init__(self, window: int):
        self.window = window
        self.anchor = min(ANCHOR, window)
        self.codes: list[np.ndarray] = []
        self.columns: dict[str, list[np.ndarray]] = {name: [] for name in ("at", "doc", "place", "under", "print")}
        self.prefix: list[list[np.ndarray]] = [[] for _ in range(self.anchor)]
        self.words = self.size = 0

    def add(self, texts: list[bytes], ids: np.ndarray, known: np.ndarray, prints: bool) -> None:
        w = Words(texts)
        n = self.window
        inside = window_mask(w.first, n, len(w.hash))
        owner = w.owner()
        at = np.flatnonzero(inside & known[owner[: len(inside)]]) if len(inside) else np.zeros(0, np.int64)
        grams = [gram_hash(w.hash, k) for k in range(1, self.anchor + 1)]
        if len(at):
            least, offset = grams[-1][at], np.zeros(len(at), np.int64)
            for k in range(1, n - self.anchor + 1):
                here = grams[-1][at + k]
                lower = here < least
                least = np.where(lower, here, least)
                offset[lower] = k
            under = at + offset
        else:
            under = at
        told = np.fromiter((zlib.crc32(t) for t in texts), np.int64, len(texts))
        self.codes.append((w.hash >> np.uint64(48)).astype(np.uint16))
        own = owner[at] if len(at) else at
        values = {"at": at + self.words, "doc": ids[own], "place": (told[own] << 32) | (at - w.first[own]), "under": under + self.words, "print": gram_hash(w.hash, n)[at] if prints else at}
        for name, held in self.columns.items():
            held.append(values[name])
        for held, g in zip(self.prefix, grams, strict=True):
            held.append(g[under])
        self.words += len(w.hash)
        self.size += len(at)

    def arrays(self) -> tuple[np.ndarray, dict[str, np.ndarray], list[np.ndarray]]:
        return np.concatenate(self.codes), {k: np.concatenate(v) for k, v in self.columns.items()}, [np.concatenate(x) for x in self.prefix]


def _batches(rows: Iterator[pa.RecordBatch], window: int, prints: bool) -> Iterator[Batch]:
    held = Batch(window)
    for batch in rows:
        ids = batch["doc_id"].fill_null(0).to_numpy(zero_copy_only=False)
        known = batch["doc_id"].is_valid().to_numpy(zero_copy_only=False)
        for first, block in blocks(batch["text"].to_pylist()):
            held.add(block, ids[first : first + len(block)], known[first : first + len(block)], prints)
            if held.size >= BATCH:
                yield held
                held = Batch(window)
    if held.size:
        yield held


def _starts(changes: np.ndarray) -> np.ndarray:
    """Starts of runs, from whether each place but the first differs from the one before."""
    return np.flatnonzero(np.concatenate(([True], changes)))


def survey(docs: DataFrame, window: int, cells: int) -> np.ndarray:
    """Suffixes by length of the anchor's prefix and cell of its hash."""

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros((min(ANCHOR, window), cells), np.int64)
        for batch in _batches(rows, window, False):
            for i, h in enumerate(batch.arrays()[2]):
                counts[i] += np.bincount((h % np.uint64(cells)).astype(np.int64), minlength=cells)
        level, cell = np.nonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in (level, cell, counts[level, cell])], names=["level", "cell", "n"])

    sums = docs.mapInArrow(run, "level long, cell long, n long").groupBy("level", "cell").agg(F.sum("n").alias("n")).toPandas()  # ANCHOR x cells rows at most
    counts = np.zeros((min(ANCHOR, window), cells), np.int64)
    counts[sums["level"].to_numpy(np.int64), sums["cell"].to_numpy(np.int64)] = sums["n"].to_numpy(np.int64)
    return counts


def plan(counts: np.ndarray, parts: int) -> np.ndarray:
    """Part of each (level, cell); -1 where the prefix is too common and a longer one decides.

    Groups go, largest first, to the part that has least.
    """
    room = max(1, int(counts[-1].sum()) // parts)
    out = np.full(counts.shape, -1, np.int32)
    groups, open_share = [], 1.0
    for level in range(len(counts)):
        fits = (counts[level] * open_share <= room) | (level == len(counts) - 1)
        groups += [(counts[level, c] * open_share, level, c) for c in np.flatnonzero(fits & (counts[level] > 0))]
        open_share *= counts[level][~fits].sum() / max(1, counts[level].sum())
        out[level, fits & (counts[level] == 0)] = 0
    load = [(0.0, p) for p in range(parts)]
    for n, level, cell in sorted(groups, reverse=True):
        held, p = heapq.heappop(load)
        out[level, cell] = p
        heapq.heappush(load, (held + n, p))
    return out


_DEALT = "part int, repeats boolean, ids binary, places binary, lengths binary, codes binary, checks binary"


def _dealt(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int32(), pa.bool_(), *[pa.binary()] * 5)
    columns = zip(*rows, strict=True) if rows else [[] for _ in kinds]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["part", "repeats", "ids", "places", "lengths", "codes", "checks"])


def _joined(doc: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(doc, place, length) of runs of adjoining windows."""
    order = np.lexsort((place, doc))
    doc, place = doc[order], place[order]
    if not len(doc):
        return doc, place, doc
    first = _starts((doc[1:] != doc[:-1]) | (place[1:] != place[:-1] + 1))
    return doc[first], place[first], np.diff(np.append(first, len(doc)))


def _spread(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Places starts[i], starts[i] + 1, ... of all runs, one after the other."""
    ends = np.cumsum(lengths)
    return np.arange(ends[-1]) + np.repeat(starts - (ends - lengths), lengths)


def deal(docs: DataFrame, window: int, assigned: np.ndarray, parts: int, finer: int) -> DataFrame:
    """Segments of a batch for a part; and repeats found in the batch, for any part."""
    cells = np.uint64(assigned.shape[1])

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _batches(rows, window, True):
            codes, x, prefix = batch.arrays()
            order = np.lexsort((x["doc"], x["print"]))
            p, d = x["print"][order], x["doc"][order]
            first = _starts(p[1:] != p[:-1])
            least = np.repeat(d[first], np.diff(np.append(first, len(p))))
            goes = np.ones(len(p), bool)
            goes[order] = d == least
            doc, place, length = _joined(x["doc"][~goes], x["place"][~goes])
            out = [(int(p[0] % np.uint64(parts * finer)), True, doc.tobytes(), place.tobytes(), length.astype(np.int64).tobytes(), b"", b"")] if len(doc) else []
            at, doc, place, under = (x[name][goes] for name in ("at", "doc", "place", "under"))
            check = x["print"][goes].astype(np.uint16)
            prefix = [h[goes] for h in prefix]
            part = np.full(len(at), -1, np.int32)
            for level, h in enumerate(prefix):
                part = np.where(part < 0, assigned[level][(h % cells).astype(np.int64)], part)
            part = part * finer + (prefix[-1] // cells % np.uint64(finer)).astype(np.int32)
            # Segments: adjoining suffixes under one anchor.
            first = _starts((at[1:] != at[:-1] + 1) | (under[1:] != under[:-1]) | (place[1:] != place[:-1] + 1))
            count = np.diff(np.append(first, len(at)))
            order = np.argsort(part[first], kind="stable")
            first, count = first[order], count[order]
            edges = np.append(_starts(part[first][1:] != part[first][:-1]), len(first))
            held = 0
            for a, b in zip(edges[:-1], edges[1:], strict=True):
                words = count[a:b] + window - 1
                spread = _spread(at[first[a:b]], words)
                out.append((int(part[first[a]]), False, doc[first[a:b]].tobytes(), place[first[a:b]].tobytes(), count[a:b].astype(np.uint16).tobytes(), codes[spread].tobytes(), check[_spread(first[a:b], count[a:b])].tobytes()))
                held += len(spread)
                if held > SENT:
                    yield _dealt(out)
                    out, held = [], 0
            if out:
                yield _dealt(out)

    return docs.mapInArrow(run, _DEALT)


def ordered_suffixes(codes: np.ndarray, at: np.ndarray, depth: int, check: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(order, common): suffixes at[order] ascending by their words, and how many words, up to `depth`, each shares with the one before.

    Words are taken four at a time, and only for suffixes that some other still agrees with.  Where `check` differs,
    so does some word in spite of its code; then `common` stays below `depth`.
    """
    order = np.arange(len(at))
    common = np.zeros(len(at), np.int64)
    fresh = np.zeros(len(at), bool)  # parted from the one before
    fresh[:1] = True
    live = order.copy()
    for step in range(0, depth + 4, 4):
        if not len(live):
            break
        if step >= depth:
            if check is None:
                break
            key = check[order[live]].astype(np.uint64)
        else:
            key = np.zeros(len(live), np.uint64)
            for k in range(4):
                key <<= np.uint64(16)
                if step + k < depth:
                    key |= codes[at[order[live]] + step + k]
        group = np.cumsum(fresh[live])
        by = np.lexsort((key, group)) if step else np.argsort(key, kind="stable")
        order[live] = order[live][by]
        key, group = key[by], group[by]
        differs = (group[1:] == group[:-1]) & (key[1:] != key[:-1])
        parted = live[1:][differs]
        apart = (key[1:] ^ key[:-1])[differs]
        shared = sum((apart < np.uint64(1 << bits)).astype(np.int64) for bits in (48, 32, 16))
        common[parted] = np.minimum(step + shared, depth - 1)
        fresh[parted] = True
        alone = fresh & np.append(fresh[1:], True)
        live = np.flatnonzero(~alone)
    common[~fresh] = depth
    return order, common


def deep_nodes(common: np.ndarray, depth: int) -> np.ndarray:
    """Number of the node at `depth` that each ordered suffix is below."""
    return np.cumsum(common < depth) - 1


def subtrees(dealt: DataFrame, window: int) -> DataFrame:
    """(doc_id, place, length): runs of windows to drop."""

    def run(rows: pa.Table) -> pa.Table:
        whole = {name: rows[name].to_pylist() for name in ("repeats", "ids", "places", "lengths", "codes", "checks")}
        segments = [i for i, r in enumerate(whole["repeats"]) if not r]
        said = [i for i, r in enumerate(whole["repeats"]) if r]
        read = lambda name, kind, chosen: np.concatenate([np.zeros(0, kind), *[np.frombuffer(whole[name][i], kind) for i in chosen]])
        doc, place, length = read("ids", np.int64, said), read("places", np.int64, said), read("lengths", np.int64, said)
        if segments:
            ids, places, count = read("ids", np.int64, segments), read("places", np.int64, segments), read("lengths", np.uint16, segments).astype(np.int64)
            codes = read("codes", np.uint16, segments)
            words = count + window - 1
            offset = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
            at = np.repeat(np.cumsum(words) - words, count) + offset
            order, common = ordered_suffixes(codes, at, window, read("checks", np.uint16, segments))
            node = deep_nodes(common, window)
            whose, where = np.repeat(ids, count)[order], (np.repeat(places, count) + offset)[order]
            least = np.full(node[-1] + 1, np.iinfo(np.int64).max)
            np.minimum.at(least, node, whose)
            later = whose > least[node]
            found = _joined(whose[later], where[later])
            doc, place, length = (np.concatenate(pair) for pair in zip((doc, place, length), found, strict=True))
        return pa.table([pa.array(doc), pa.array(place), pa.array(length.astype(np.int32))], names=["doc_id", "place", "length"])

    return dealt.groupBy("part").applyInArrow(run, "doc_id long, place long, length int")


def remove_repeats(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, n_words, n_removed, kept (remaining words joined by one space), repeats (word spans removed)."""
    ship(docs.sparkSession)
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    counts = survey(slim, window, 1 << 14)
    parts = parts_for(int(counts[-1].sum()), PART)
    planned = min(parts, MOST_PLANNED)
    told = subtrees(deal(slim, window, plan(counts, planned), planned, parts_for(parts, planned)), window)
    by_doc = told.groupBy("doc_id").agg(F.collect_list(F.struct("place", "length")).alias("told"))

    def drop(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in rows:
            out: list[tuple] = []
            for doc_id, text, runs in zip(batch["doc_id"].to_pylist(), batch["text"], batch["told"].to_pylist(), strict=True):
                raw = (text.as_py() or "").encode("utf-8", "surrogatepass")
                words = raw.split()
                spans = _spans(runs, zlib.crc32(raw), window) if runs else []
                kept, at, gone = [], 0, 0
                for a, b in spans:
                    kept += words[at:a]
                    gone += b - a
                    at = b
                out.append((doc_id, len(words), gone, b" ".join([*kept, *words[at:]]).decode("utf-8", "surrogatepass"), [x for span in spans for x in span]))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.list_(pa.int64()))
            columns = zip(*out, strict=True) if out else [[] for _ in kinds]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["doc_id", "n_words", "n_removed", "kept", "repeats"])

    texts = slim.where("doc_id is not null").join(by_doc, "doc_id", "left").unionByName(slim.where("doc_id is null"), allowMissingColumns=True)
    return texts.select("doc_id", "text", "told").mapInArrow(drop, "doc_id long, n_words long, n_removed long, kept string, repeats array<long>")


def _spans(runs: list[dict], own: int, window: int) -> list[tuple[int, int]]:
    """Spans of words covered by a text's runs of windows, joined where they meet."""
    out: list[tuple[int, int]] = []
    for place, length in sorted((r["place"] & 0xFFFFFFFF, r["length"]) for r in runs if (r["place"] >> 32) & 0xFFFFFFFF == own):
        end = place + length + window - 1
        if out and place <= out[-1][1]:
            out[-1] = (out[-1][0], max(out[-1][1], end))
        else:
            out.append((place, end))
    return out


def op10_substring(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = remove_repeats(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))
