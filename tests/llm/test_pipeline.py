"""Each stage of the corpus pipeline on what its predecessor kept, against brute force."""

import random

import numpy as np
import public_tokenizers
import pytest

import corpus_pipeline
from geopat.llm import packing
from tests.llm.test_operators import WORD, _by_force


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    rng = random.Random(6)
    words = [f"w{i}" for i in range(300)]
    line = lambda n: " ".join(rng.choices(words, k=n))
    shared = [line(8) for _ in range(3)]
    rows, labels = [], []
    for i in range(160):
        good = i % 4 != 1
        text = "\n".join(line(rng.choice((6, 9, 12))) for _ in range(8)) if good else " ".join(f"{w}###!!!" for w in rng.choices(words, k=60))
        if good and i % 5 == 0:
            text = f"{shared[i % 3]}\n{text}"
        if good and i % 10 == 2:
            at = text.split()
            at[7] = "changed"
            rows.append((1000 + i, " ".join(at), "en", "s1", 0, 7))
        rows.append((i, text, "en", f"s{i % 3}", len(text), 7))
        labels.append((i, int(good), 0))
    rows += [(500, None, None, None, None, 7), (501, "", "en", "s0", 0, 7), (None, "a text without an id but words", "en", "s0", 30, 7)]
    out = tmp_path_factory.mktemp("tables")
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, row int").write.parquet(f"{out}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{out}/labels.parquet")
    return str(out)


def test_stages(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    kept = {}
    for name, stage in corpus_pipeline.STAGES:
        before = docs.collect()
        docs = spark.createDataFrame((after := stage(spark, docs, folder)).collect(), after.schema)
        kept[name] = (before, docs.collect())
        if name != "packing":
            assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars", "row"]

    before, after = kept["quality"]
    bad = {r.doc_id for r in before if "###" in (r.text or "")}
    assert {r.doc_id for r in before} - {r.doc_id for r in after} - bad <= {500, 501} and not bad & {r.doc_id for r in after}

    before, after = kept["line_dedup"]
    left = _by_force({r.doc_id: r.text or "" for r in before if r.doc_id is not None}, 8)
    expected = {i: t for i, (_, n, t) in left.items() if not (n and not t.strip())}
    assert {r.doc_id: r.text for r in after if r.doc_id is not None} == expected and any(n for _, n, _ in left.values())
    assert all(r.n_chars == len(r.text) for r in after if left.get(r.doc_id, (0, 0))[1])

    before, after = kept["near_dedup"]
    sets = {}
    for r in before:
        w = WORD.findall((r.text or "").lower())
        sets[r.doc_id] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} or {tuple(w)}
    ids = sorted(i for i in sets if i is not None)
    root = {i: i for i in ids}
    for _ in ids:
        for i in ids:
            for j in ids:
                if 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
                    root[i] = root[j] = min(root[i], root[j])
        if all(root[root[i]] == root[i] for i in ids):
            break
    assert sorted(r.doc_id for r in after if r.doc_id is not None) == [i for i in ids if root[i] == i]

    before, after = kept["mixing"]
    size = {r.doc_id: len(WORD.findall(r.text or "")) for r in before}
    total = {s: sum(size[r.doc_id] for r in before if r.source == s) for s in {r.source for r in before}}
    order = sorted(s for s in total if s is not None) + [None] * (None in total)
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(order)}
    target, open_ = {}, set(total)
    while open_:
        rest = sum(total.values()) - sum(target.values())
        full = {s for s in open_ if rest * weight[s] / sum(weight[x] for x in open_) > 3 * total[s]}
        target |= {s: 3 * total[s] if full else rest * weight[s] / sum(weight[x] for x in open_) for s in (full or open_)}
        open_ -= full or open_
    for s, aim in target.items():
        assert abs(sum(size[r.doc_id] for r in after if r.source == s) - aim) <= max(size.values())
    assert all(sum(x.doc_id == r.doc_id for x in after) <= 3 for r in before)

    before, after = kept["packing"]
    full = packing.encoder(public_tokenizers.path(packing.VOCABULARY)).full
    tokens = {r.doc_id: len(full.encode(r.text or "", add_special_tokens=False).ids) + 1 for r in before}
    assert len({r.sequence_id for r in after}) == len(after) and all(r.length & (r.length - 1) == 0 and r.doc_tokens == tokens[r.doc_id] for r in after)
    assert sum(r.length for r in after) == sum(tokens[r.doc_id] for r in before)


def test_fast_tokens_are_the_files():
    own = packing.encoder(public_tokenizers.path(packing.VOCABULARY))
    rng = np.random.default_rng(1)
    for _ in range(1500):
        points = rng.choice([rng.integers(32, 127), rng.integers(160, 0x600), rng.integers(0x3040, 0x30FF), rng.integers(0x1F300, 0x1F600), 10, 32, 0x200B], size=rng.integers(1, 40))
        text = "".join(map(chr, points))
        assert own.ids(text) == own.full.encode(text, add_special_tokens=False).ids
