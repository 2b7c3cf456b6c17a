"""Frequent tree shapes: embedded or induced, unordered or ordered, mined level by level on packed trees.

A shape is a preorder sequence of (depth, label).  A tree's shapes are built from its leaves
upwards as sets of forests, not from their images, whose number grows with the subsets of
equal siblings.
"""

from __future__ import annotations

from ast import literal_eval
from collections import Counter
from collections.abc import Iterable, Iterator
from functools import lru_cache

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geopat.plans.scratch import written
from geopat.plans.ship import ship

Shape = tuple[tuple[int, str], ...]


def adaptive_support(trees: Column, a: float = 0.004, b: float = 1.5, c: float = 0.05) -> Column:
    """Minimum support of a set of trees: falls with their number towards c."""
    return F.exp(-(a * trees + b)) + c


def _children(shape: Shape) -> list[Shape]:
    out: list[list] = []
    for depth, label in shape[1:]:
        if depth == shape[0][0] + 1:
            out.append([])
        out[-1].append((depth, label))
    return [tuple(x) for x in out]


@lru_cache(maxsize=100_000)
def canonical(shape: Shape) -> Shape:
    """Sibling order that makes the sequence largest; a sequence that extends another is larger."""
    if len(shape) == 1:
        return shape
    parts = sorted((canonical(c) for c in _children(shape)), reverse=True)
    return (shape[0], *(x for p in parts for x in p))


@lru_cache(maxsize=100_000)
def text(shape: Shape, ordered: bool = False) -> str:
    """Labels with children in parentheses, siblings alphabetical unless ordered."""
    parts = [text(c, ordered) for c in _children(shape)]
    return shape[0][1] + (f"({','.join(parts if ordered else sorted(parts))})" if parts else "")


class Tree:
    """Nodes in preorder: label, parent place, and place after the last descendant."""

    def __init__(self, nodes: list[int], parents: list[int | None], labels: list[str], starts: list[int]):
        below: dict = {}
        for i in sorted(range(len(nodes)), key=lambda i: (starts[i], nodes[i])):
            below.setdefault(parents[i], []).append(i)
        self.label: list[str] = []
        self.parent: list[int] = []
        self.end: list[int] = []
        self.kinds: tuple | None = None
        todo = [(i, -1) for i in reversed(below.get(None, []))]
        known = set(nodes)
        if not todo:
            todo = [(i, -1) for i in range(len(nodes)) if parents[i] not in known]
        while todo:
            i, up = todo.pop()
            at = len(self.label)
            self.label.append(labels[i])
            self.parent.append(up)
            self.end.append(at + 1)
            todo += [(j, at) for j in reversed(below.get(nodes[i], []))]
        for at in range(len(self.label) - 1, 0, -1):
            if self.parent[at] >= 0:
                self.end[self.parent[at]] = max(self.end[self.parent[at]], self.end[at])


def _grow(tree: Tree, shape: Shape, images: list[tuple[int, ...]], kind: str, siblings: str, ordered: bool) -> dict[Shape, list[tuple[int, ...]]]:
    """Shapes of one node more, with their images; for containment of single shapes."""
    path: list[int] = []
    for i, (depth, _) in enumerate(shape):
        path = [*path[:depth], i]
    kids: dict[int, list[int]] = {i: [] for i in path}
    stack: list[int] = []
    for i, (depth, _) in enumerate(shape):
        stack = [*stack[:depth], i]
        if depth and stack[depth - 1] in kids:
            kids[stack[depth - 1]].append(i)
    out: dict[Shape, list[tuple[int, ...]]] = {}
    for image in images:
        for at in path:
            x = image[at]
            for y in range(x + 1, tree.end[x]):
                if kind == "induced" and tree.parent[y] != x:
                    continue
                if siblings == "any":
                    if y in image:
                        continue
                elif any(not (tree.end[image[c]] <= y or tree.end[y] <= image[c]) for c in kids[at]):
                    continue
                if ordered and kids[at] and y < tree.end[image[kids[at][-1]]]:
                    continue
                out.setdefault((*shape, (shape[at][0] + 1, tree.label[y])), []).append((*image, y))
    return out


#: Subtrees of up to so many nodes are numbered, so that equal ones are looked at once.
SMALL = 12
#: A level forgets what it knows of small subtrees, and a task its numbers, beyond so many of them.
MOST_HELD = 500_000


class Book:
    """Numbers for tree shapes and for forests (multisets of shapes, sequences where ordered), so that both are compared as integers."""

    def __init__(self, ordered: bool = False):
        self.ordered = ordered
        self.parts: list[tuple[int, ...]] = [()]
        self.weight = [0]
        self.shape: list[tuple[str, int]] = []
        self.alone: list[int] = []
        self._forests: dict = {(): 0}
        self._trees: dict = {}
        self._joined: dict = {}
        self._less: dict = {}
        self._turned: dict = {}
        self._codes: dict = {}
        self._texts: dict = {}
        self.kinds: list[tuple[str, tuple[int, ...], int]] = []
        self._kinds: dict = {}

    def full(self) -> bool:
        return len(self.parts) + len(self._joined) + len(self.kinds) > MOST_HELD

    def kinds_of(self, tree: Tree) -> list[int]:
        """A number for each node's subtree, equal for equal ones; -1 where it is not small."""
        if tree.kinds is None or tree.kinds[0] is not self:
            out = [-1] * len(tree.label)
            below: dict[int, list[int]] = {}
            for x in range(len(out) - 1, -1, -1):
                if tree.end[x] - x <= SMALL:
                    children = below.pop(x, [])
                    key = (tree.label[x], tuple(reversed(children)) if self.ordered else tuple(sorted(children)))
                    found = self._kinds.get(key)
                    if found is None:
                        found = self._kinds[key] = len(self.kinds)
                        self.kinds.append((*key, tree.end[x] - x))
                    out[x] = found
                if tree.parent[x] >= 0 and out[x] >= 0:
                    below.setdefault(tree.parent[x], []).append(out[x])
            tree.kinds = (self, out)
        return tree.kinds[1]

    def forest(self, parts: tuple[int, ...]) -> int:
        parts = parts if self.ordered else tuple(sorted(parts))
        found = self._forests.get(parts)
        if found is None:
            found = self._forests[parts] = len(self.parts)
            self.parts.append(parts)
            self.weight.append(sum(1 + self.weight[self.shape[p][1]] for p in parts))
        return found

    def tree(self, label: str, below: int) -> int:
        found = self._trees.get((label, below))
        if found is None:
            found = self._trees[label, below] = len(self.shape)
            self.shape.append((label, below))
            self.alone.append(self.forest((found,)))
        return found

    def joined(self, a: int, b: int) -> int:
        found = self._joined.get((a, b))
        if found is None:
            found = self._joined[a, b] = self.forest(self.parts[a] + self.parts[b])
        return found

    def less(self, forest: int) -> tuple[int, ...]:
        """The forests that are left when one leaf goes."""
        found = self._less.get(forest)
        if found is None:
            parts, out = self.parts[forest], set()
            for i, part in enumerate(parts):
                label, below = self.shape[part]
                kept = [()] if not below else [(self.tree(label, x),) for x in self.less(below)]
                out.update(self.forest((*parts[:i], *k, *parts[i + 1 :])) for k in kept)
            found = self._less[forest] = tuple(out)
        return found

    def turned(self, label: str, forest: int) -> tuple[int, ...]:
        """The forests in which a node of that label has taken some of the forest's trees, or none, below it."""
        found = self._turned.get((label, forest))
        if found is None:
            parts, out = self.parts[forest], set()
            for mask in range(1 << len(parts)):
                taken = tuple(p for i, p in enumerate(parts) if mask >> i & 1)
                out.add(self.forest((*(p for i, p in enumerate(parts) if not mask >> i & 1), self.tree(label, self.forest(taken)))))
            found = self._turned[label, forest] = tuple(out)
        return found

    def number(self, shape: Shape) -> int:
        return self.tree(shape[0][1], self.forest(tuple(self.number(c) for c in _children(shape))))

    def text(self, tree: int) -> str:
        found = self._texts.get(tree)
        if found is None:
            label, below = self.shape[tree]
            parts = [self.text(p) for p in self.parts[below]]
            found = self._texts[tree] = label + (f"({','.join(parts if self.ordered else sorted(parts))})" if parts else "")
        return found

    def code(self, tree: int) -> Shape:
        """Preorder of the shape, canonical unless ordered."""
        found = self._codes.get(tree)
        if found is None:
            label, below = self.shape[tree]
            parts = [self.code(p) for p in self.parts[below]]
            whole = ((0, label), *((d + 1, x) for p in parts for d, x in p))
            found = self._codes[tree] = whole if self.ordered else canonical(whole)
        return found


class Level:
    """Shapes of `size` nodes of a group's trees, where all frequent smaller ones are known.

    A node hands its parent the forests that lie in its subtree: each is listed once, however many images it has.  What
    is not part of a frequent shape goes at once, and a shape counts where every shape of one leaf less is frequent.
    Equal small subtrees are looked at once.
    """

    def __init__(self, book: Book, known: set[int], size: int, kind: str = "embedded", siblings: str = "disjoint", ordered: bool = False):
        self.book, self.known, self.size = book, known, size
        self.own, self.nested = kind == "induced", siblings == "any" and kind != "induced" and not ordered
        self.good = {book.shape[t][1] for t in known} | {0}
        self._whole: dict[int, bool] = {}
        self._counts: dict[int, bool] = {}
        self._pairs = _Pairs(self)
        self._seen: dict[int, tuple[list[set[int]], set[int]]] = {}
        self._offers: dict[int, list[set[int]]] = {}
        self._held = 0
        self._nothing: list[set[int]] = [{0}, *(set() for _ in range(size - 1))]

    def _fits(self, forest: int) -> bool:
        if self.book.weight[forest] < self.size - 1:
            return forest in self.good
        found = self._whole.get(forest)
        if found is None:
            found = self._whole[forest] = all(x in self.good for x in self.book.less(forest))
        return found

    def _candidate(self, label: str, forest: int) -> int | None:
        tree = self.book.tree(label, forest)
        found = self._counts.get(tree)
        if found is None:
            found = self._counts[tree] = all(self.book.tree(label, x) in self.known for x in self.book.less(forest))
        return tree if found else None

    def _with(self, handed: list[set[int]], later: list[set[int]] | None) -> list[set[int]]:
        """Forests, by size, of a child and of its later siblings."""
        if later is None:
            return handed
        out = [later[0]]
        for n in range(1, self.size):
            both = handed[n] | later[n]
            for i in range(1, n):
                if later[i]:
                    for a in handed[n - i]:
                        both.update(map(self._pairs[a].__getitem__, later[i]))
            both.discard(0)
            out.append(both)
        return out

    def _handed(self, label: str, below: list[set[int]]) -> list[set[int]]:
        """Forests, by size, that a node of that label offers its parent."""
        book = self.book
        out = [{0}, *(set() for _ in range(self.size - 1))] if self.own else [set(x) for x in below]
        for n in range(self.size - 1):
            for forest in below[n]:
                if self.nested:
                    out[n + 1].update(x for x in book.turned(label, forest) if self._fits(x))
                    continue
                tree = book.tree(label, forest)
                if tree in self.known and self._fits(book.alone[tree]):
                    out[n + 1].add(book.alone[tree])
        return out

    def _shapes(self, label: str, below: list[set[int]]) -> Iterator[int]:
        return (t for f in below[self.size - 1] if (t := self._candidate(label, f)) is not None)

    def _small(self, kind: int) -> tuple[list[set[int]], set[int]]:
        """Forests below the root of a small subtree, and the shapes in the subtree."""
        found = self._seen.get(kind)
        if found is None:
            label, children, _ = self.book.kinds[kind]
            below, shapes = None, set()
            for child in reversed(children):
                shapes |= self._small(child)[1]
                below = self._with(self._small_handed(child), below)
            below = below or self._nothing
            shapes.update(self._shapes(label, below))
            found = self._seen[kind] = (below, shapes)
            self._held += len(shapes) + sum(map(len, below))
        return found

    def _small_handed(self, kind: int) -> list[set[int]]:
        found = self._offers.get(kind)
        if found is None:
            found = self._offers[kind] = self._handed(self.book.kinds[kind][0], self._small(kind)[0])
            self._held += sum(map(len, found))
        return found

    def found(self, tree: Tree) -> set[int]:
        if self.size == 1:
            return {self.book.tree(x, 0) for x in tree.label}
        if self._held > MOST_HELD:
            self._seen, self._offers, self._held = {}, {}, 0
        out: set[int] = set()
        below: dict[int, list[set[int]]] = {}
        kinds = self.book.kinds_of(tree)
        # A node's children come to it from the last to the first; small subtrees come whole.
        for x in range(len(tree.label) - 1, -1, -1):
            up, small = tree.parent[x], kinds[x] >= 0
            if small and up >= 0 and kinds[up] >= 0:
                continue
            if small:
                out |= self._small(kinds[x])[1]
            else:
                mine = below.pop(x, None) or self._nothing
                out.update(self._shapes(tree.label[x], mine))
            if up >= 0:
                below[up] = self._with(self._small_handed(kinds[x]) if small else self._handed(tree.label[x], mine), below.get(up))
        return out


class _Pairs(dict):
    """By a forest, and then by a second one, the forest of both, or that of nothing where it does not fit the level."""

    def __init__(self, level: Level, first: int | None = None):
        self.level, self.first = level, first

    def __missing__(self, forest: int) -> _Pairs | int:
        if self.first is None:
            found = _Pairs(self.level, forest)
        else:
            both = self.level.book.joined(self.first, forest)
            found = both if self.level._fits(both) else 0
        self[forest] = found
        return found


def pack(nodes: DataFrame, group: list[str]) -> DataFrame:
    """One row per tree: group, tree, and arrays of nodes."""
    each = F.struct("node", "parent", "label", "start_us")
    return nodes.groupBy(*group, "tree").agg(F.collect_list(each).alias("nodes"))


def _trees(column: pa.Array) -> Iterator[Tree]:
    """Trees of a packed column."""
    flat = column.flatten()
    fields = [flat.field(name).to_pylist() for name in ("node", "parent", "label", "start_us")]
    at = 0
    for n in pc.list_value_length(column).to_pylist():
        yield Tree(*(f[at : at + n] for f in fields))
        at += n


def mined(trees: Iterable[Tree], enough: int, max_nodes: int, options: tuple[str, str, bool], book: Book | None = None) -> list[tuple[str, int, str, int]]:
    """(shape, size, root label, count) of the shapes of two or more nodes in at least `enough` of the trees.

    Equal trees are looked at once.  A tree without a frequent shape of one size has none of the next, since each of
    those holds one with a leaf less in the same tree.
    """
    book, known, rows = book or Book(options[2]), set(), []
    alike: dict[tuple, list] = {}
    for tree in trees:
        alike.setdefault((tuple(tree.label), tuple(tree.parent)), [tree, 0])[1] += 1
    left = list(alike.values())
    for size in range(1, max_nodes + 1):
        level, counts, lists = Level(book, known, size, *options), Counter(), []
        left = [x for x in left if len(x[0].label) >= size]
        for tree, n in left:
            lists.append(level.found(tree))
            for shape in lists[-1]:
                counts[shape] += n
        some = {t: n for t, n in counts.items() if n >= enough}
        if not some:
            break
        known |= some.keys()
        left = [x for x, found in zip(left, lists, strict=True) if not found.isdisjoint(some)]
        if size > 1:
            rows += [(book.text(t), size, book.shape[t][0], n) for t, n in some.items()]
    return rows


#: Groups of more trees are mined level by level over all tasks, smaller ones whole in one task.
MOST_TREES = 20_000


def frequent(
    nodes: DataFrame, group: list[str], min_support: float | None = None, max_nodes: int = 7, kind: str = "embedded", siblings: str = "disjoint", ordered: bool = False, most_trees: int = MOST_TREES
) -> DataFrame:
    """(group, shape, size, root_label, support_count, trees, support): shapes of two or more nodes in enough trees of their group.

    `min_support` None takes the adaptive one of each group.  A group of up to `most_trees` trees is mined in one
    task.  Trees of larger ones stay where they are; a level shuffles counts of shapes only, and sends the (few)
    frequent ones back.
    """
    ship(nodes.sparkSession)
    packed = written(pack(nodes, group))
    share = adaptive_support(F.col("trees")) if min_support is None else F.lit(min_support)
    least = written(packed.groupBy(*group).agg(F.count("*").alias("trees")).withColumn("least", F.ceil(share * F.col("trees") - 1e-9)))
    keys = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in packed.select(*group).schema)
    options = (kind, siblings, ordered)
    books: list[Book] = []  # each task has its own

    def whole(table: pa.Table) -> pa.Table:
        if not books or books[0].full():
            books[:] = [Book(ordered)]
        rows = mined((t for chunk in table["nodes"].chunks for t in _trees(chunk)), table["least"][0].as_py(), max_nodes, options, books[0])
        return pa.table({**{g: table[g].slice(0, 1).take(pa.array([0] * len(rows), pa.int64())) for g in group}, **{n: pa.array([r[i] for r in rows], t) for i, (n, t) in enumerate(_FOUND.items())}})

    sized = packed.join(F.broadcast(least), group)
    small = sized.where(F.col("trees") <= most_trees).select(*group, "least", "nodes")
    found = small.groupBy(*group).applyInArrow(whole, f"{keys}, shape string, size long, root_label string, support_count long")
    big = least.where(F.col("trees") > most_trees)
    if not big.isEmpty():
        found = found.unionByName(_by_level(written(sized.where(F.col("trees") > most_trees).select(*group, "nodes")), big, group, keys, max_nodes, options))
    out = written(found).join(F.broadcast(least), group)
    return out.select(*group, "shape", "size", "root_label", "support_count", "trees", F.round(F.col("support_count") / F.col("trees"), 6).alias("support"))


#: Columns of a found shape beside its group's.
_FOUND = {"shape": pa.string(), "size": pa.int64(), "root_label": pa.string(), "support_count": pa.int64()}


def _by_level(packed: DataFrame, least: DataFrame, group: list[str], keys: str, max_nodes: int, options: tuple) -> DataFrame:
    """(group, shape, size, root_label, support_count) of large groups: a pass over all trees for each level."""
    ordered = options[2]
    known: dict[tuple, list[Shape]] = {}
    kept: list[DataFrame] = []
    for size in range(1, max_nodes + 1):

        def run(batches: Iterator[pa.RecordBatch], size: int = size, known: dict = known) -> Iterator[pa.RecordBatch]:
            book, levels = Book(ordered), {}
            for batch in batches:
                counts: Counter = Counter()
                for key, tree in zip(zip(*(batch[g].to_pylist() for g in group), strict=True), _trees(batch["nodes"]), strict=True):
                    if size > 1 and key not in known:
                        continue
                    if key not in levels:
                        levels[key] = Level(book, {book.number(s) for s in known.get(key, ())}, size, *options)
                    counts.update((key, t) for t in levels[key].found(tree))
                rows = [(*key, repr(code := book.code(t)), text(code, ordered), size, code[0][1], n) for (key, t), n in counts.items()]
                names = [*group, "code", *_FOUND]
                kinds = [*(batch.schema.field(g).type for g in group), pa.string(), *_FOUND.values()]
                yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds)], names)

        listed = packed.where(F.size("nodes") >= size).mapInArrow(run, f"{keys}, code string, shape string, size long, root_label string, support_count long")
        counted = listed.groupBy(*group, "code", "shape", "size", "root_label").agg(F.sum("support_count").alias("support_count"))
        level = written(counted.join(F.broadcast(least.select(*group, "least")), group).where("support_count >= least").drop("least"))
        found = level.select(*group, "code").collect()  # shapes that are frequent, not occurrences
        if not found:
            break
        kept.append(level.drop("code"))
        known = {key: list(shapes) for key, shapes in known.items()}
        for row in found:
            known.setdefault(tuple(row[:-1]), []).append(literal_eval(row[-1]))
    out = kept[0].where("size > 1") if kept else packed.select(*group, F.lit("").alias("shape"), F.lit(0).cast("long").alias("size"), F.lit("").alias("root_label"), F.lit(0).cast("long").alias("support_count")).where("false")
    for level in kept[1:]:
        out = out.unionByName(level)
    return out


def state_core(shapes: DataFrame) -> DataFrame:
    """(state, shape, size, root_label): union of a state's city shapes."""
    return shapes.select("state", "shape", "size", "root_label").distinct()


def catalogue(core: DataFrame) -> DataFrame:
    """One row: (state, shape) pairs, unique shapes, fewest and most nodes."""
    return core.agg(F.count("*").alias("state_shapes"), F.countDistinct("shape").alias("unique_shapes"), F.min("size").alias("fewest"), F.max("size").alias("most"))


def shape_sql(adaptive: bool, fixed: float = 0.02) -> str:
    """WITH-list items up to `s2` (state, city, shape, ...) of two-node shapes for DuckDB, after `g`."""
    share = "exp(-(0.004 * trees + 1.5)) + 0.05" if adaptive else str(fixed)
    return f"""
nt as (select state, city, count(distinct tree) trees from g group by 1, 2),
an as (select tree, state, city, node top, node low, label top_label, label low_label, parent up from g
  union all select an.tree, an.state, an.city, g.node, an.low, g.label, an.low_label, g.parent from an join g on g.tree = an.tree and g.node = an.up),
c2 as (select state, city, top_label || '(' || low_label || ')' shape, top_label root_label, count(distinct tree) support_count from an where top <> low group by 1, 2, 3, 4),
s2 as (select c2.*, trees, round(support_count / trees, 6) support from c2 join nt using (state, city) where support_count >= ceil(({share}) * trees - 1e-9))
"""


def three_sql(adaptive: bool, group: str = "state, city", name: str = "s3", fixed: float = 0.02) -> str:
    """WITH-list items up to `name`: shapes of two and three nodes by group for DuckDB, after the items of `shape_sql`."""
    share = "exp(-(0.004 * trees + 1.5)) + 0.05" if adaptive else str(fixed)
    return f"""
{name}_n as (select {group}, count(distinct tree) trees from g group by all),
{name}_o as (
  select tree, state, city, 2::bigint size, top_label root_label, top_label || '(' || low_label || ')' shape from an where top <> low
  union all select a.tree, a.state, a.city, 3, a.top_label, a.top_label || '(' || a.low_label || '(' || b.low_label || '))' from an a join an b on a.tree = b.tree and a.low = b.top where a.top <> a.low and b.top <> b.low
  union all select a.tree, a.state, a.city, 3, a.top_label, a.top_label || '(' || least(a.low_label, b.low_label) || ',' || greatest(a.low_label, b.low_label) || ')' from an a join an b on a.tree = b.tree and a.top = b.top and a.low < b.low
    where a.top <> a.low and b.top <> b.low and not exists (select 1 from an x where x.tree = a.tree and ((x.top = a.low and x.low = b.low) or (x.top = b.low and x.low = a.low)))),
{name} as (select {group}, shape, size, root_label, support_count, trees, round(support_count / trees, 6) support
  from (select {group}, shape, size, root_label, count(distinct tree) support_count from {name}_o group by all) join {name}_n using ({group}) where support_count >= ceil(({share}) * trees - 1e-9))
"""
