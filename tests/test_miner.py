"""The miner on trees with many equal siblings, in both of its ways, and reduced lists."""

import random
import sys
from pathlib import Path

import pytest

from geopat.operators import mine, shapes
from geopat.operators.forest import build
from geopat.plans.scratch import written

sys.path.insert(0, str(Path(__file__).resolve().parent))
from test_core import brute, trees  # noqa: E402


def found(nodes, least, **options):
    return {r["shape"]: r.support_count for r in mine.frequent(nodes, ["g"], least, **options).collect()}


@pytest.mark.parametrize("most_trees", [0, 100])
def test_equal_leaves_are_not_listed_by_subset(spark, most_trees):
    """A root with 60 equal leaves has 50 million images of its largest shape."""
    star = [("a", None), *[("b", 0)] * 60]
    assert found(trees(spark, star, star[:5]), 0.01, most_trees=most_trees) == {f"a({','.join('b' * n)})": 2 if n < 5 else 1 for n in range(1, 7)}


def some_trees(seed, n=5):
    rng = random.Random(seed)
    return [[("a", None), *[(rng.choice("abc"), rng.randrange(i)) for i in range(1, rng.randint(3, 8))]] for _ in range(n)]


@pytest.mark.parametrize("most_trees", [0, 100])
def test_both_ways_are_enumeration(spark, most_trees):
    forest = some_trees(7)
    lists = [brute(t) for t in forest]
    count = {x: sum(x in s for s in lists) for s in lists for x in s if "(" in x}
    assert found(trees(spark, *forest), 0.4, max_nodes=8, most_trees=most_trees) == {x: n for x, n in count.items() if n >= 2}


@pytest.mark.parametrize("options", [{"kind": "induced"}, {"siblings": "any"}, {"ordered": True}])
def test_variants_hold_in_their_trees(spark, options):
    """Counts agree with containment, which works on images."""
    forest = some_trees(11)
    whole = [mine.Tree(list(range(len(t))), [p for _, p in t], [x for x, _ in t], list(range(len(t)))) for t in forest]
    got = found(trees(spark, *forest), 0.2, max_nodes=4, **options)
    assert got == found(trees(spark, *forest), 0.2, max_nodes=4, most_trees=0, **options)
    assert len(got) > 20 and all(sum(shapes.contains(t, shapes.parse(x), **options) for t in whole) == n for x, n in got.items())


@pytest.mark.parametrize("closed", [False, True])
def test_reduced_is_comparison_of_all_pairs(spark, closed):
    listed = mine.frequent(trees(spark, *some_trees(5)), ["g"], 0.4, max_nodes=6)
    rows = {r["shape"]: (r["size"], r.support_count) for r in listed.collect()}
    inside = lambda x, y: rows[x][0] < rows[y][0] and (not closed or rows[x][1] == rows[y][1]) and shapes.contains(shapes.tree_of(shapes.parse(y)), shapes.parse(x))
    assert {r["shape"] for r in shapes.reduced(listed, ["g"], closed).collect()} == {x for x in rows if not any(inside(x, y) for y in rows)}


@pytest.mark.parametrize("closed", [False, True])
def test_reduced_broadcasts_no_list(spark, closed):
    """A written list is small for its rows, so by its size it would be gathered on the driver."""
    listed = written(mine.frequent(trees(spark, *some_trees(5)), ["g"], 0.4, max_nodes=6))
    out = shapes.reduced(listed, ["g"], closed)
    assert out.collect() and "Broadcast" not in out._jdf.queryExecution().executedPlan().toString()


def test_shapes_of_one_node_less():
    assert shapes.fewer("a(b(c,d))") == ("a(b(c))", "a(b(d))", "a(c,d)", "b(c,d)")
    assert shapes.fewer("a(b,b)") == ("a(b)",)


def test_equal_and_spent_trees_are_not_looked_at_again(monkeypatch):
    """Fifty equal trees count as one, and a tree without a frequent shape leaves."""
    tree = lambda *rows: mine.Tree(list(range(len(rows))), [p for _, p in rows], [x for x, _ in rows], list(range(len(rows))))
    looked, found = [], mine.Level.found
    monkeypatch.setattr(mine.Level, "found", lambda self, t: looked.append((self.size, tuple(t.label))) or found(self, t))
    forest = [tree(("a", None), ("b", 0), ("c", 1)) for _ in range(50)] + [tree(("x", None), ("y", 0), ("z", 0))]
    got = mine.mined(forest, 2, 7, ("embedded", "disjoint", False))
    assert sorted(got) == [("a(b(c))", 3, "a", 50), ("a(b)", 2, "a", 50), ("a(c)", 2, "a", 50), ("b(c)", 2, "b", 50)]
    assert looked == [(1, tuple("abc")), (1, tuple("xyz")), (2, tuple("abc")), (3, tuple("abc"))]


def test_equal_subtrees_are_looked_at_once():
    """Forty trees that differ at the root, all with the same three nodes below it: each level joins and hands over theirs once."""
    tree = lambda *rows: mine.Tree(list(range(len(rows))), [p for _, p in rows], [x for x, _ in rows], list(range(len(rows))))
    forest = [tree((f"r{i}", None), ("a", 0), ("b", 1), ("c", 1)) for i in range(40)]
    book = mine.Book()
    known = {book.number(s) for x in "abc" for s in [((0, x),)]}
    level, handed = mine.Level(book, known, 2), []
    keep = level._handed
    level._handed = lambda label, below: handed.append(label) or keep(label, below)
    found = {book.text(t) for x in forest for t in level.found(x)}
    assert sorted(handed) == ["a", "b", "c"] and found == {"a(b)", "a(c)"}


def test_numbers_are_shared_by_groups_of_a_task():
    """A second group's result does not depend on the first one's, whichever shapes were frequent there."""
    tree = lambda rows: mine.Tree(list(range(len(rows))), [p for _, p in rows], [x for x, _ in rows], list(range(len(rows))))
    for options in [(k, s, o) for k in ("embedded", "induced") for s in ("disjoint", "any") for o in (False, True)]:
        book = mine.Book(options[2])
        for seed in range(6):
            forest = some_trees(seed, 8)
            assert sorted(mine.mined(map(tree, forest), 2, 6, options, book)) == sorted(mine.mined(map(tree, forest), 2, 6, options))
            assert book.kinds and not book.full()


def test_large_and_small_subtrees_meet(monkeypatch):
    """The bound on small subtrees decides what is numbered, not what is found."""
    tree = lambda rows: mine.Tree(list(range(len(rows))), [p for _, p in rows], [x for x, _ in rows], list(range(len(rows))))
    for options in [(k, s, o) for k in ("embedded", "induced") for s in ("disjoint", "any") for o in (False, True)]:
        got = []
        for small, held in ((0, 0), (1, 500_000), (3, 0), (12, 500_000)):
            monkeypatch.setattr(mine, "SMALL", small)
            monkeypatch.setattr(mine, "MOST_HELD", held)
            got.append(sorted(mine.mined(map(tree, some_trees(3, 12)), 3, 7, options)))
        assert got[0] and all(x == got[0] for x in got)


def test_parents_are_made_once(spark):
    made = spark.sparkContext.accumulator(0)

    def rows(batches):
        for batch in batches:
            made.add(batch.num_rows)
            yield batch

    links = spark.createDataFrame([(n, n - 1) for n in range(1, 10)], "node long, parent long").mapInArrow(rows, "node long, parent long")
    assert {(r.tree, r.node, r.depth) for r in build(links).collect()} == {(0, n, n) for n in range(10)}
    assert made.value == 9
