"""Operators against brute force, on documents with nulls, empty and long texts, copies and clashing columns."""

import hashlib
import random
import re
import time
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from geopat.llm import lines, mixing, neardup, packing, pii, quality, rules, substring, toxicity, vectors
from geopat.llm.wordhash import Words

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, component string, _row string, b string"


def make(seed=5, n=90):
    rng = random.Random(seed)
    vocabulary = [f"w{i}" for i in range(60)]
    texts = [None, "", " \n\t", "one", "One", "one two", "ONE two", "a b c d", "a b c d e", " ".join(rng.choices(vocabulary, k=4000))]
    for _ in range(n):
        kind = rng.random()
        if kind < 0.4 and len(texts) > 12:
            words = (rng.choice(texts[9:]) or "x").split(" ")
            for _ in range(rng.choice((0, 1, 3))):
                words[rng.randrange(len(words))] = rng.choice(vocabulary)
            texts.append(" ".join(words))
        else:
            texts.append("".join(rng.choice(vocabulary) + rng.choice((" ", " ", " ", "\n")) for _ in range(rng.choice((5, 20, 60, 200)))))
    rows = [(i, t, None if i % 7 == 0 else "en", ("src0", "src1", None)[i % 3], None, "x", "y", "z") for i, t in enumerate(texts)]
    rng.shuffle(rows)
    return rows


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(make(), SCHEMA)


@pytest.fixture(scope="module")
def texts():
    return {r[0]: r[1] or "" for r in make()}


@pytest.fixture(scope="module")
def nothing(spark):
    return spark.createDataFrame([], SCHEMA)


def test_word_hash():
    w = Words([b"a bb  a", b"", b"\xc3\xa9 a"])
    assert list(w.first) == [0, 3, 3, 5]
    assert w.hash[0] == w.hash[2] == w.hash[4] != w.hash[1]


@pytest.mark.parametrize("words", [2, 5])
def test_near_duplicates(spark, docs, texts, words, monkeypatch):
    sets = {}
    for i, t in texts.items():
        w = [x.translate({c: c + 32 for c in range(65, 91)}) for x in WORD.findall(t)]
        sets[i] = {tuple(w[k : k + words]) for k in range(len(w) - words + 1)} or ({tuple(w)} if w else set())
    root = {i: i for i in sets}
    for _ in sets:
        for i in sets:
            for j in sets:
                if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
                    root[i] = root[j] = min(root[i], root[j])
        if all(root[root[i]] == root[i] for i in root):
            break
    for short, local, gather in ((24, 8, 1000), (2, 2, 10)) if words == 2 else ((24, 2, 10),):
        for name, value in (("SHORT", short), ("LOCAL", local), ("GATHER", gather)):
            monkeypatch.setattr(neardup, name, value)
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", gather)
        got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in neardup.near_duplicates(docs, words).collect()}
        assert got == {i: (len(sets[i]), root[i], root[i] == i) for i in sets}
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 1000)


def test_shingles_are_sorted_text_by_text(monkeypatch):
    """A block's hashes are those of each text alone, and no sort takes the whole block by two keys."""
    monkeypatch.setattr(neardup.np, "lexsort", None)
    rng = random.Random(3)
    block = [" ".join(rng.choices("abcAB", k=rng.randrange(9))).encode() for _ in range(50)]
    for words in (1, 2, 5):
        edges, h = neardup.shingles(block, words)
        assert len(edges) == 51 and len(h) == edges[-1]
        for i, text in enumerate(block):
            alone, mine = neardup.shingles([text], words)[1].tolist(), h[edges[i] : edges[i + 1]].tolist()
            split = text.lower().split()
            n = len({tuple(split[j : j + words]) for j in range(max(1, len(split) - words + 1))}) if split else 0
            assert mine == alone == sorted(set(mine)) and len(mine) == n


def test_substring(docs, texts, monkeypatch):
    expected, first = {}, {}
    for i in sorted(texts):
        w = WORD.findall(texts[i])
        gone = [False] * len(w)
        for k in range(len(w) - 12):
            if first.setdefault(tuple(w[k : k + 13]), i) < i:
                gone[k : k + 13] = [True] * 13
        expected[i] = (len(w), sum(gone), " ".join(x for x, g in zip(w, gone, strict=True) if not g))
    for batch, part in ((1_000_000, 1_500_000), (300, 200)):
        monkeypatch.setattr(substring, "BATCH", batch)
        monkeypatch.setattr(substring, "PART", part)
        monkeypatch.setattr(substring, "MOST_PLANNED", 8)
        assert {r.doc_id: (r.n_words, r.n_removed, r.kept) for r in substring.remove_repeats(docs).collect()} == expected


def test_substring_odd_rows(spark):
    """Rows that share an id are judged by their own words; null ids neither lose nor take."""
    a, b = " ".join(f"a{k}" for k in range(30)), " ".join(f"b{k}" for k in range(30))
    rows = [(None, a, 1), (2, a, 2), (2, "x y " + b, 3), (5, f"{b} q {a}", 4), (5, a, 5), (7, None, 6)]
    docs = spark.createDataFrame(rows, "doc_id int, text string, n_removed int")
    got = sorted((r.doc_id or 0, r.n_words, r.n_removed) for r in substring.remove_repeats(docs).collect())
    assert got == [(0, 30, 0), (2, 30, 0), (2, 32, 0), (5, 30, 30), (5, 61, 60), (7, 0, 0)]


def test_suffix_order():
    rng = np.random.default_rng(0)
    codes = rng.integers(0, 3, 400).astype(np.uint16)
    at = rng.permutation(380)
    for depth in (13, 8, 4, 1, 2):
        order, common = substring.ordered_suffixes(codes, at, depth)
        suffix = [tuple(codes[at[i] : at[i] + depth]) for i in order]
        assert suffix == sorted(suffix)
        for k in range(1, len(suffix)):
            assert common[k] == next((j for j in range(depth) if suffix[k][j] != suffix[k - 1][j]), depth)
        assert substring.deep_nodes(common, depth).max() + 1 == len(set(suffix))
        check = rng.integers(0, 2, 380).astype(np.uint16)
        order, common = substring.ordered_suffixes(codes, at, depth, check)
        assert substring.deep_nodes(common, depth).max() + 1 == len({(*codes[at[i] : at[i] + depth], check[i]) for i in range(380)})


def test_rules(docs, texts):
    for r in rules.judge(docs).collect():
        t = texts[r.doc_id]
        w, held = WORD.findall(t), [x for x in t.split("\n") if WORD.search(x)]
        windows = [tuple(w[k : k + 8]) for k in range(len(w) - 7)]
        n, covered = Counter(windows), set()
        for k, x in enumerate(windows):
            if n[x] > 1:
                covered.update(range(k, k + 8))
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(held) - len(set(held)), len(covered))
        assert r.base_failed == (len(w) < 20 or 100 * len(covered) > 30 * len(w)) and (not r.kept or not r.base_failed)


def test_fences_follow_their_group(spark):
    rng = random.Random(4)

    def text(n, width, symbols, capitals, repeats):
        w = ["".join(rng.choices("abcdefghijklmnop", k=rng.choice((width - 1, width, width, width + 1)))) for _ in range(n)]
        w = [x.upper() if k < capitals else x for k, x in enumerate(w)] + ["##"] * symbols + w[:9] * repeats
        return " ".join(w)

    plain = [(i, text(60, 6, i % 2, i % 3, 0), "en", "plain") for i in range(240)]
    code = [(1000 + i, text(60, 10, 4 + i % 9, 8 + i % 9, i % 2), "en", "code") for i in range(240)]
    odd = {"symbol_share": text(60, 6, 10, 0, 0), "capital_share": text(60, 6, 0, 14, 0), "repeat_share": text(60, 6, 0, 0, 1), "mean_word": text(60, 9, 0, 0, 0)}
    probes = [(k, t, "en", source) for s, source in enumerate(("plain", "code")) for k, t in enumerate(odd.values(), 2000 + 10 * s)]
    rows = {r.doc_id: r for r in rules.judge(spark.createDataFrame(plain + code + probes, "doc_id long, text string, lang string, source string")).collect()}
    for k, name in enumerate(odd):
        in_plain, in_code = rows[2000 + k], rows[2010 + k]
        assert in_plain[name] == in_code[name] and not in_plain.base_failed
        assert name in in_plain.failed and name not in in_code.failed and not in_plain.kept
    assert sum(not rows[i].kept for i, *_ in plain + code) < 24


def test_sketch_quantiles(spark):
    """A sketch's quantile lies within its bucket's width of the exact one, whatever parts the sketch was merged from."""
    rng = random.Random(7)
    values = [(f"g{i % 3}", rng.choice((0.0, rng.random() ** 4, 5 * rng.random()))) for i in range(900)]
    stats = spark.createDataFrame(values, "g string, x double")
    whole = rules.sketches(stats.repartition(1), ["g"], ["x"])
    parts = rules.sketches(stats.repartition(9), ["g"], ["x"])
    assert sorted(whole.collect()) == sorted(parts.collect())
    for r in rules.quantiles(whole, ["g"], {"mid": 0.5, "high": 0.75}).collect():
        held = sorted(x for g, x in values if g == r.g)
        for got, share in ((r.mid, 0.5), (r.high, 0.75)):
            exact = held[int(np.ceil(share * len(held))) - 1]
            assert r.total == len(held) and abs(got - exact) <= max(0.005 * exact, rules.SMALLEST)


def test_packing_round_trip(docs, texts):
    rows, own = packing.pack(docs).collect(), packing.encoder(__import__("public_tokenizers").path(packing.VOCABULARY))
    assert len({r.sequence_id for r in rows}) == len(rows) and all(r.length & (r.length - 1) == 0 and r.length <= 1024 and r.offset == 0 for r in rows)
    for i, t in texts.items():
        mine = sorted((r.start, r.ids) for r in rows if r.doc_id == i)
        ids = np.frombuffer(b"".join(x for _, x in mine), "<u4").tolist()
        assert ids == [*own.full.encode(t, add_special_tokens=False).ids, 0]
    assert own.ids("a<|endoftext|>b") == own.full.encode("a<|endoftext|>b", add_special_tokens=False).ids


def test_mixing(docs, texts):
    rows = mixing.mix(docs).collect()
    size = Counter()
    for r in rows:
        assert r["size"] == len(WORD.findall(texts[r.doc_id])) and 0 <= r.taken <= 3 * r["size"]
        size[r.source] += r["size"]
    target = {r.source: r.target for r in rows}
    assert abs(sum(target.values()) - sum(size.values())) < 1e-6 and all(target[s] <= 3 * size[s] + 1e-6 for s in size)
    for s in size:
        assert abs(sum(r.taken for r in rows if r.source == s) - target[s]) <= max(r["size"] for r in rows if r.source == s)
    assert sorted(map(str, rows)) == sorted(map(str, mixing.mix(docs.repartition(7)).collect()))
    assert mixing.repeat_documents(docs).count() == sum(r.copies for r in rows)


def _patience(a, b, shows):
    """Matched places (i, j) of two lists of lines, written without the operator's helpers: heads, tails, then a longest increasing run of lines unique on both sides, by dynamic programming."""
    if not a or not b:
        return []
    if a[0] == b[0]:
        return [(0, 0)] + [(i + 1, j + 1) for i, j in _patience(a[1:], b[1:], shows)]
    if a[-1] == b[-1]:
        return _patience(a[:-1], b[:-1], shows) + [(len(a) - 1, len(b) - 1)]
    spots = [(a.index(x), b.index(x)) for x in a if shows(x) and a.count(x) == 1 == b.count(x)]
    if not spots:
        return []
    best = []  # of equally long runs, the one with the smallest places in b, from its end on
    for k, (_, j) in enumerate(spots):
        before = min((best[m] for m in range(k) if spots[m][1] < j), key=lambda x: (-len(x), x[-1][1]), default=[])
        best.append([*before, spots[k]])
    run = min(best, key=lambda x: (-len(x), x[-1][1]))
    out = []
    for (i, j), (i2, j2) in zip([(-1, -1), *run], [*run, (len(a), len(b))], strict=True):
        out += [(i, j)] if i >= 0 else []
        out += [(i + 1 + x, j + 1 + y) for x, y in _patience(a[i + 1 : i2], b[j + 1 : j2], shows)]
    return out


def _by_force(texts, rare):
    """doc_id -> (lines, removed, text left), from lines as strings."""
    shows = lambda x: len(x.split()) >= 3 or len(x.encode()) >= 24
    held = {i: [x.strip(" \t\x0b\x0c\r") for x in t.split("\n")] for i, t in texts.items()}
    classes = {}
    for i in sorted(held):
        classes.setdefault(tuple(held[i]), i)
    lead = sorted(classes.values())
    holders = Counter(x for i in lead for x in {x for x in held[i] if shows(x)})
    out = {}
    for i, b in held.items():
        first, gone = classes[tuple(b)], set()
        if first < i and (len(texts[i].split()) >= 3 or len(texts[i].strip().encode()) >= 24):
            gone = set(range(len(b)))
        elif first == i:
            for e in (e for e in lead if e < i):
                if {x for x in held[e] if shows(x) and holders[x] <= rare} & set(b):
                    places = sorted(j for _, j in _patience(held[e], b, shows))
                    while places:
                        n = next((n for n in range(1, len(places)) if places[n] != places[0] + n), len(places))
                        if any(shows(b[j]) for j in places[:n]):
                            gone.update(places[:n])
                        places = places[n:]
            gone |= {j for j, x in enumerate(b) if shows(x) and holders[x] > rare and any(x in held[e] for e in lead if e < i)}
            # Runs between showing lines.
            runs = lambda lines: [(max(p, -1) + 1, q) for p, q in zip([-1, *[k for k, x in enumerate(lines) if shows(x)]], [*[k for k, x in enumerate(lines) if shows(x)], len(lines)], strict=True) if q - p > 1]
            around = lambda lines, p, q: (lines[p - 1] if p else None, *lines[p:q], lines[q] if q < len(lines) else None)
            for p, q in runs(b) if any(map(shows, b)) else ():
                sides = {x for x in (p - 1, q) if 0 <= x < len(b)}
                if sides <= gone and any(around(held[e], *r) == around(b, p, q) for e in lead if e < i and any(map(shows, held[e])) for r in runs(held[e])):
                    gone.update(range(p, q))
        out[i] = (len(b), len(gone), "\n".join(x for j, x in enumerate(texts[i].split("\n")) if j not in gone))
    return out


def _lines_left(docs):
    return {r.row.doc_id: (r.n_lines, r.n_removed, r.left or "") for r in lines.without_lines(docs, lines.removals(docs)).collect()}


def test_lines(docs, texts, spark, monkeypatch):
    assert _lines_left(docs) == _by_force(texts, lines.RARE)
    assert lines.aligned([1, 3, 5, 7], [3, 5, 9, 7]) == [0, 1, 3]
    rng = random.Random(8)
    pool = [f"the line number {k}" for k in range(9)] + ["", "ab", "}", " \t", "short"]
    made = {i: "\n".join(rng.choices(pool, k=rng.choice((1, 3, 6, 12)))) if i % 6 else rng.choice(["a b c\nd", "one two", "", "x\ny", "x\ny\nz w\n"]) for i in range(1, 70)}
    some = spark.createDataFrame([(i, t, 1, "n") for i, t in made.items()], "doc_id int, text string, n_removed int, told string")
    for rare in (100, 8, 2):
        monkeypatch.setattr(lines, "RARE", rare)
        assert _lines_left(some) == _by_force(made, rare)


def test_lines_of_every_earlier_holder(spark):
    l, q, r, z = (f"the line {x} here" for x in "LQRZ")
    texts = {1: f"{l}\n{q}\n{r}", 2: f"{z}\n{l}", 3: f"{q}\n{r}\n{l}"}
    assert {i: n for i, (_, n, _) in _lines_left(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).items()} == {1: 0, 2: 1, 3: 3}


def test_lines_odd_rows(spark):
    """Null ids neither lose nor take lines; rows that share an id are judged by their own lines."""
    a, b = "a first long line\nsecond long line here", "a third long line\nown words of it"
    rows = [(None, a, 1), (None, a, 2), (1, a, 3), (5, a, 4), (5, b, 5), (5, b, 6), (7, b, 7), (8, None, 8)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, n_chars int")
    left = {r.row.n_chars: r.n_removed for r in lines.without_lines(docs, lines.removals(docs)).collect()}
    assert left == {1: 0, 2: 0, 3: 0, 4: 2, 5: 0, 6: 0, 7: 2, 8: 0}
    assert sorted(r.doc_id or 0 for r in lines.clean_documents(docs).collect()) == [0, 0, 1, 5, 5, 8]


def test_vectors(spark):
    rng = np.random.default_rng(1)
    base = rng.normal(size=(12, 6))
    rows = [(i, (base[i % 12] + (i // 12) * 0.03 * rng.normal(size=6)).astype("float32").tolist(), i % 2) for i in range(60)]
    rows += [(60, rows[3][1], 1), (61, [0.0] * 6, 1), (62, None, 1), (63, [float("nan")] * 6, 1), (64, rows[3][1], None), (65, [1.0, None, 0.0, 0.0, 0.0, 0.0], 1), (66, [1.0, 2.0], 1)]
    sound = {i: (np.array(v), x) for i, v, x in rows if x is not None and v and None not in v and np.isfinite(v).all() and np.any(v)}
    links = {i: set() for i, _, _ in rows}
    for i, (v, x) in sound.items():
        for j, (u, y) in sound.items():
            if i != j and x == y and len(u) == len(v) and v @ u / np.sqrt((v @ v) * (u @ u)) >= 0.98:
                links[i].add(j)
    root = {i: i for i in links}
    for _ in root:
        for i in links:
            for j in links[i]:
                root[i] = root[j] = min(root[i], root[j])
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in vectors.near_vectors(df).collect()}
    assert got == {i: (len(links[i]), root[i], root[i] == i) for i in links} and any(links.values())
    assert vectors.near_vectors(df.where("false")).count() == 0


def test_personal_data():
    text = "é a.b@c-d.org, 10.0.0.255 and 4111 1111 1111 1111 or +1 (555) 010-9999; 1.2.3.999"
    base, spans = pii.find(text)
    assert [k for k, _, _ in base] == ["email", "ip", "card", "phone"] and spans == base
    assert text[base[0][1] : base[0][2]] == "a.b@c-d.org"
    for hidden, kind in (("jane [at] site [dot] org", "email"), ("jane at site dot org", "email"), ("ｊo@ехa.com", "email"), ("+１ 555 010 9999", "phone"), ("plus one five five five zero one zero nine nine nine nine", "phone")):
        _, found = pii.find(f"é {hidden}!")
        assert [(k, f"é {hidden}!"[a:b]) for k, a, b in found] == [(kind, hidden)]
    for clean in ("we met at noon. dot", "at the site", "one two three", ""):
        assert pii.find(clean) == ([], [])
    assert pii.find(None) == ([], []) and pii.mask("a b@c.d e", pii.find("a b@c.d e")[1]) == "a <email> e"


def test_personal_data_partly_disguised():
    for hidden, kind in (
        ("192[.]168[.]1[.]1", "ip"), ("10 dot 0 dot 0 dot 1", "ip"), ("one zero dot zero dot zero dot one", "ip"), ("+1 555 five five five 0199", "phone"), ("jane at example.com", "email"),
        ("4111 1111 1111 one one one one", "card"),
    ):
        _, found = pii.find(f"é {hidden}!")
        assert [(k, f"é {hidden}!"[a:b]) for k, a, b in found] == [(kind, hidden)]
    text = "é a@b.example [dot] com, seven 192[.]168[.]1[.]1"
    base, spans = pii.find(text)
    assert [text[a:b] for _, a, b in base] == ["a@b.example"] and pii.mask(text, spans) == "é <email>, seven <ip>"
    for plain in ("+1 555 010 9999, one of", "+1 (848) 555-1373 Un", "look at 3.5 and five", "10 dot 5, two or 3", "999 dot 0 dot 0 dot 1"):
        assert pii.find(plain)[0] == pii.find(plain)[1]


def _contract_spans(text):
    """Base spans straight from the contract's patterns."""
    digits = lambda x: re.sub("[^0-9]", "", x)

    def luhn(d):
        return sum(sum(map(int, str(int(c) * 2))) if k % 2 else int(c) for k, c in enumerate(reversed(d))) % 10 == 0

    rules = (
        (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda m: True),
        (r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda m: max(map(int, m.split("."))) <= 255),
        (r"[0-9]([\x20-]?[0-9])+", lambda m: 14 <= len(digits(m)) <= 19 and luhn(digits(m))),
        (r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: 10 <= len(digits(m)) <= 15),
    )
    found = [(m.start(), k, m.end()) for k, (p, good) in enumerate(rules) for m in re.finditer(p, text) if good(m.group())]
    return [(pii.KINDS[k], a, b) for a, k, b in sorted(found)]


def test_base_spans_are_the_contracts():
    rng = random.Random(3)
    bits = ["a", "Z9", "@", ".", "-", " ", "+", "+1", "(", ")", "1", "12", "255", "256", "007", "4111 1111 1111 1111", "4111", "x@y.z", "1.2.3.4", "\n", "é", "%", "_", "٣", "..", "@@", "5500-0000-0000-0004", "+1 555 010 9999"]
    for _ in range(6000):
        text = "".join(rng.choices(bits, k=rng.choice((3, 8, 20, 40))))
        assert pii.find(text)[0] == _contract_spans(text), text


def test_personal_data_in_long_texts():
    """Time is linear: texts that are one run, of what patterns start with, take seconds at most."""
    n = 200_000
    blobs = ("1" * n, "a" * n + " a (dot) b", "(" * n + "dot", "one" + " " * n + "x", " a at b" * (n // 7), "a dot " * (n // 6), "+1 " * (n // 3), "1." * (n // 2), "a@" * (n // 2), "one two " * (n // 8), "\u200b" * n, "a (at) b " * (n // 9), "plus " * (n // 5))
    started = time.time()
    for blob in blobs:
        pii.find(blob)
    assert time.time() - started < 40
    tail = "jane (at) site (dot) org"
    text = "x" * n + " " + tail
    assert pii.find(text)[1] == [("email", n + 1, len(text))]


def test_classifiers(spark):
    rng = random.Random(2)
    words = [f"w{i}" for i in range(200)]
    rows, labels = [], []
    for i in range(400):
        toxic, good = int(i % 5 == 0), int(i % 4 != 1)
        w = rng.choices(words, k=60) + ["Scum", "idiot,"][: 2 * toxic]
        rng.shuffle(w)
        rows.append((i, " ".join(x if good else x + "###" for x in w)))
        labels.append((i, good, toxic))
    rows += [(400, None), (401, "")]
    docs, marks = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    judged = {r.doc_id: r for r in quality.score(docs, quality.learn(docs, marks)).collect()}
    flagged = {r.doc_id: r for r in toxicity.score(docs, toxicity.learn(docs, marks)).collect()}
    assert len(judged) == len(flagged) == 402
    assert sum(judged[i].predicted == q for i, q, _ in labels) > 390 and sum(flagged[i].flagged == bool(t) for i, _, t in labels) > 390
    none = marks.where("false")
    assert {r.score for r in quality.score(docs, quality.learn(docs, none)).collect()} == {0.5}
    assert not any(r.flagged for r in toxicity.score(docs, toxicity.learn(docs, none)).collect())


def test_empty_tables(nothing):
    for df in (neardup.near_duplicates(nothing), substring.remove_repeats(nothing), rules.judge(nothing), packing.pack(nothing), mixing.mix(nothing), pii.scan(nothing), lines.clean_documents(nothing), neardup.keep_one(nothing)):
        assert df.count() == 0


def test_columns_pass_through(spark, docs):
    odd = [*lines.without_lines(docs, lines.removals(docs)).columns, "_gone", "id", "told", "_text", "_lines", "copies", "rate", "score", "predicted", "a.b"]
    more = docs.select("*", *[F.lit(i).alias(c) for i, c in enumerate(odd)])
    labels = spark.createDataFrame([(i, i % 2) for i in range(20)], "doc_id long, quality int")
    for df in (lines.clean_documents(more), neardup.keep_one(more), mixing.repeat_documents(more), quality.keep_good(more, labels)):
        assert df.columns == more.columns and df.count() >= 0
