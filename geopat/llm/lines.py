"""Line dedup by pairwise alignment.

A line's hash is that of its text without outer blanks.  A line of at least LEAST_WORDS
words or LEAST_BYTES bytes can show that documents overlap.  Documents of equal lines are
one class, of which the first (by id) is compared; if the text as a whole is long enough to
show overlap, the others lose all of it.

Rare lines, those that at most RARE classes hold, lead to pairs: every later holder is
aligned with every earlier one.  Patience alignment hangs on lines that are unique in both
documents: it takes the longest rising run of these, recurses between them and grows over
equal neighbours.  An aligned block with at least one line that can show overlap is deleted
from the later document.

Lines that more classes hold give no pairs, which would grow with the square of the holders.
Such a line is a one-line block that its first holder shares with all others, and goes from
every later holder.  A run of short and blank lines goes with the two lines around it,
if an earlier document has the same run between the same two.  So no line is left out for
being common, and work grows with the text.

Alignment is always against texts as given, so the order of pairs does not matter.  Null and
empty texts have one blank line and lose nothing.  Rows with a null id lose nothing and
take nothing.  Rows that share an id are judged each by its own lines, and never against each
other; repeated rows and ties so fare alike.  A text whose lines are all deleted becomes
empty.  Other columns pass through, whatever their names.  An empty table gives no rows.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geopat.plans.scratch import hot_join

from .common import materialise, ship, table

LEAST_WORDS = 3
LEAST_BYTES = 24
RARE = 8
BLANKS = " \t\x0b\x0c\r"
_EDGE = b"\0" * 8


def _shows(words: int, size: int) -> bool:
    return words >= LEAST_WORDS or size >= LEAST_BYTES


def line_hashes(text: str | None) -> np.ndarray:
    """A hash per line; the lowest bit says that the line can show overlap, and blank lines are 0."""
    out = []
    for line in (text or "").split("\n"):
        bare = line.strip(BLANKS).encode("utf-8", "surrogatepass")
        h = xxhash.xxh3_64_intdigest(bare) & ~1 if bare else 0
        out.append(h | _shows(len(bare.split()), len(bare)))
    return np.array(out, np.uint64)


def runs_between(lines: np.ndarray) -> list[tuple[int, int, int]]:
    """(start, end, key) of the runs of lines that show nothing; the key, an even number, says what the run and the lines around it are."""
    shows = np.flatnonzero(lines & np.uint64(1))
    if not len(shows):
        return []
    out, raw = [], lines.tobytes()
    for left, right in zip([-1, *shows.tolist()], [*shows.tolist(), len(lines)], strict=True):
        if right - left > 1:
            around = (raw[8 * left : 8 * left + 8] if left >= 0 else _EDGE) + raw[8 * (left + 1) : 8 * right + 8]
            out.append((left + 1, right, xxhash.xxh3_64_intdigest(around, 1 + (right == len(lines))) & ~1))
    return out


def _rising(places: list[int]) -> list[int]:
    """Indices of a longest strictly rising run."""
    tails: list[int] = []
    last: list[int] = []
    before = [-1] * len(places)
    for i, p in enumerate(places):
        k = bisect_left(tails, p)
        if k == len(tails):
            tails.append(p)
            last.append(i)
        else:
            tails[k], last[k] = p, i
        before[i] = last[k - 1] if k else -1
    out, i = [], last[-1] if last else -1
    while i >= 0:
        out.append(i)
        i = before[i]
    return out[::-1]


def aligned(a: list[int], b: list[int]) -> list[int]:
    """Places in b that patience alignment matches with places in a."""
    matched: list[int] = []
    todo = [(0, len(a), 0, len(b))]
    while todo:
        a0, a1, b0, b1 = todo.pop()
        while a0 < a1 and b0 < b1 and a[a0] == b[b0]:
            matched.append(b0)
            a0, b0 = a0 + 1, b0 + 1
        while a0 < a1 and b0 < b1 and a[a1 - 1] == b[b1 - 1]:
            matched.append(b1 - 1)
            a1, b1 = a1 - 1, b1 - 1
        if a0 >= a1 or b0 >= b1:
            continue
        seen_a: dict[int, int] = {}
        for i in range(a0, a1):
            seen_a[a[i]] = -1 if a[i] in seen_a else i
        seen_b: dict[int, int] = {}
        for j in range(b0, b1):
            seen_b[b[j]] = -1 if b[j] in seen_b else j
        anchors = [(i, seen_b[h]) for h, i in seen_a.items() if i >= 0 and h & 1 and seen_b.get(h, -1) >= 0]
        if not anchors:
            continue
        anchors.sort()
        chosen = [anchors[i] for i in _rising([j for _, j in anchors])]
        for (i, j), (i2, j2) in zip([(a0 - 1, b0 - 1), *chosen], [*chosen, (a1, b1)], strict=True):
            if i >= a0:
                matched.append(j)
            if i + 1 < i2 and j + 1 < j2:
                todo.append((i + 1, i2, j + 1, j2))
    return sorted(matched)


def common_blocks(a: np.ndarray, b: np.ndarray) -> list[int]:
    """Places in b of aligned blocks that hold a line which can show overlap."""
    held = b.tolist()
    out: list[int] = []
    block: list[int] = []
    for j in [*aligned(a.tolist(), held), -1]:
        if block and j != block[-1] + 1:
            if any(held[x] & 1 for x in block):
                out += block
            block = []
        block.append(j)
    return out


def _digest(lines: np.ndarray) -> int:
    return xxhash.xxh3_64_intdigest(lines.tobytes(), 3) - (1 << 63)


def _hashed(docs: DataFrame) -> DataFrame:
    """Per known row: its lines' hashes, two digests of them, whether the text as a whole can show overlap, and its distinct keys (lines that show overlap, and runs between)."""

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in rows:
            out = []
            for doc_id, text in zip(batch["doc_id"].to_pylist(), batch["text"], strict=True):
                whole = text.as_py() or ""
                lines = line_hashes(whole)
                keys = np.unique(np.concatenate((lines[(lines & np.uint64(1)) == 1], np.array([k for *_, k in runs_between(lines)], np.uint64))))
                raw = lines.tobytes()
                out.append((doc_id, _digest(lines), xxhash.xxh3_64_intdigest(raw, 4) - (1 << 63), raw, _shows(len(whole.split()), len(whole.strip())), keys.view(np.int64).tolist()))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.bool_(), pa.list_(pa.int64()))
            columns = zip(*out, strict=True) if out else [[] for _ in kinds]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["doc_id", "d1", "d2", "lines", "whole", "keys"])

    known = docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return known.mapInArrow(run, "doc_id long, d1 long, d2 long, lines binary, whole boolean, keys array<long>")


def _align(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in rows:
        out = [common_blocks(np.frombuffer(a, np.uint64), np.frombuffer(b, np.uint64)) for a, b in zip(batch["a"].to_pylist(), batch["b"].to_pylist(), strict=True)]
        yield pa.RecordBatch.from_arrays([batch["doc_id"], batch["d1"], pa.array(out, pa.list_(pa.int32()))], names=["doc_id", "d1", "places"])


def removals(docs: DataFrame) -> DataFrame:
    """(doc_id, told): what a document loses, as an array of (d1, places, keys).

    d1 is the digest of the lines that the entry is meant for, null for all.  Places and keys both null mean all
    lines.  Documents that lose none are absent.
    """
    ship(docs.sparkSession)
    held = materialise(_hashed(docs))
    alike = held.groupBy("d1", "d2").agg(F.min("doc_id").alias("leader"), F.first("lines").alias("lines"), F.first("whole").alias("whole"), F.first("keys").alias("keys"), F.count("*").alias("n"))
    classes = materialise(alike)
    leaders = classes.select(F.col("leader").alias("doc_id"), "d1", "lines", "keys")
    many = classes.where("n > 1 and whole").select("d1", F.col("d2").alias("e2"), "leader", "n")
    slim = held.select("doc_id", "d1", "d2")
    copies = hot_join(slim, many, "d1", "n", held.count()).where("d2 = e2 and leader < doc_id").select("doc_id", "d1", F.lit(None).cast("array<int>").alias("places"), F.lit(None).cast("array<long>").alias("keys"))

    entries = leaders.select("doc_id", F.explode("keys").alias("key"))
    shared = materialise(entries.groupBy("key").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last"), F.count("*").alias("n")).where("first < last").drop("last"))
    met = materialise(hot_join(entries, shared, "key", "n", shared.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]))
    is_line = F.col("key").bitwiseAND(F.lit(1)) == 1
    common = met.where((~is_line | (F.col("n") > RARE)) & (F.col("first") < F.col("doc_id")))
    by_key = common.groupBy("doc_id").agg(F.collect_set("key").alias("keys")).select("doc_id", F.lit(None).cast("long").alias("d1"), F.lit(None).cast("array<int>").alias("places"), "keys")

    of_line = met.where(is_line & (F.col("n") <= RARE)).groupBy("key").agg(F.sort_array(F.collect_set("doc_id")).alias("ids"))  # RARE ids at most
    each = F.flatten(F.transform("ids", lambda x, i: F.transform(F.slice("ids", 1, i), lambda y: F.struct(x.alias("doc_id"), y.alias("first")))))
    pairs = of_line.select(F.inline(each)).distinct()
    earlier = leaders.select(F.col("doc_id").alias("first"), F.col("lines").alias("a"))
    later = leaders.select("doc_id", "d1", F.col("lines").alias("b"))
    found = pairs.join(later, "doc_id").join(earlier, "first").select("doc_id", "d1", "a", "b").mapInArrow(_align, "doc_id long, d1 long, places array<int>").where("size(places) > 0")
    by_pair = found.groupBy("doc_id", "d1").agg(F.array_distinct(F.flatten(F.collect_list("places"))).alias("places")).withColumn("keys", F.lit(None).cast("array<long>"))

    every = copies.unionByName(by_key).unionByName(by_pair)
    return every.groupBy("doc_id").agg(F.collect_set(F.struct("d1", "places", "keys")).alias("told"))


def _gone(lines: np.ndarray, told: list[dict]) -> np.ndarray:
    """Which lines of a text the entries meant for it delete."""
    out = np.zeros(len(lines), bool)
    own, keys = _digest(lines), set()
    for entry in told:
        if entry["d1"] is not None and entry["d1"] != own:
            continue
        if entry["places"] is None and entry["keys"] is None:
            out[:] = True
        out[entry["places"] or []] = True
        keys.update(entry["keys"] or ())
    if keys:
        out |= np.isin(lines.view(np.int64), np.array([k for k in keys if k & 1], np.int64))
        for start, end, key in runs_between(lines):
            around = ([start - 1] if start else []) + ([end] if end < len(lines) else [])
            if key - (1 << 64) * (key >> 63) in keys and out[around].all():
                out[start:end] = True
    return out


def without_lines(docs: DataFrame, gone: DataFrame) -> DataFrame:
    """row (the row as given, text apart), left (the text that is left), n_lines, n_removed."""
    ship(docs.sparkSession)
    names = [c for c in docs.columns if c != "text"]
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("row"), "text", F.col("doc_id").cast("long").alias("id"))
    told = packed.join(gone.select(F.col("doc_id").alias("id"), "told"), "id", "left").select("row", "text", "told")

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in rows:
            texts, n_lines, n_removed = [], [], []
            for text, entries in zip(batch["text"].to_pylist(), batch["told"].to_pylist(), strict=True):
                if not entries:
                    texts.append(text)
                    n_lines.append((text or "").count("\n") + 1)
                    n_removed.append(0)
                    continue
                drop = _gone(line_hashes(text), entries)
                parts = (text or "").split("\n")
                n_lines.append(len(parts))
                n_removed.append(int(drop.sum()))
                texts.append("\n".join(p for p, d in zip(parts, drop.tolist(), strict=True) if not d) if drop.any() else text)
            yield pa.RecordBatch.from_arrays([batch["row"], pa.array(texts, pa.string()), pa.array(n_lines, pa.int64()), pa.array(n_removed, pa.int64())], names=["row", "left", "n_lines", "n_removed"])

    schema = told.select("row").schema.add("left", "string").add("n_lines", "long").add("n_removed", "long")
    return told.mapInArrow(run, schema)


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    kept = without_lines(docs, removals(docs))
    return kept.select("row.doc_id", "n_lines", "n_removed", F.sha2(F.coalesce("left", F.lit("")), 256).alias("kept_sha256"))


def clean_documents(docs: DataFrame) -> DataFrame:
    """The documents without their repeated lines; columns as in `docs`.  One that had words and has none left goes."""
    kept = without_lines(docs, removals(docs))
    bare = F.length(F.translate(F.coalesce("left", F.lit("")), " \t\n\x0b\x0c\r", "")) == 0
    changed = F.col("n_removed") > 0

    def column(name: str):  # noqa: ANN202
        if name == "text":
            return F.col("left").alias(name)
        given = F.col("row").getField(name)
        if name == "n_chars":
            return F.when(changed, F.length("left")).otherwise(given).cast(docs.schema[name].dataType).alias(name)
        return given.alias(name)

    return kept.where(~(changed & bare)).select(*[column(c) for c in docs.columns])
