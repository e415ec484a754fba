"""Near copies by shingles beside all pairs."""

import random

import numpy as np
import pyarrow as pa
import pytest

from backtrail.llm import near_copies
import corpus_pipeline


def plain_set(text):
    w = (text or "").lower().split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def plain_kept(rows):
    """Ids of the smallest of each component, all pairs compared."""
    sets = [(i, plain_set(t)) for i, t in sorted(rows)]
    root = {i: i for i, _ in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for k, (i, a) in enumerate(sets):
        for j, b in sets[:k]:
            if 5 * len(a & b) >= 4 * len(a | b):
                x, y = sorted((find(i), find(j)))
                root[y] = x
    return sorted(i for i in root if root[i] == i)


@pytest.mark.parametrize("sf", ["sf0.01"])
def test_stage_keeps_what_all_pairs_keep(spark, sf):
    docs = spark.read.parquet(f"/root/testdata/{sf}/documents.parquet")
    kept = corpus_pipeline.drop_near_copies(spark, docs, None)
    assert kept.columns == docs.columns
    assert sorted(r["doc_id"] for r in kept.collect()) == plain_kept([tuple(r) for r in docs.select("doc_id", "text").collect()])


def test_chains_of_edits_are_one_group(spark):
    """Each text is near the one before it only, so that groups of a key are linked beyond their first members."""
    rng = random.Random(3)
    words = [f"w{rng.randrange(10**6)}" for _ in range(300)]
    rows = [(0, " ".join(words))]
    for i in range(1, 40):
        for k in rng.sample(range(300), 3):
            words[k] = f"e{i}x{k}"
        rows.append((i, " ".join(words)))
    rows += [(100, None), (101, ""), (102, "a b c"), (103, "A b  c"), (104, "a b d")]
    kept = near_copies.keep_one(spark.createDataFrame(rows, "doc_id long, text string"))
    assert sorted(r["doc_id"] for r in kept.collect()) == plain_kept(rows) == [0, 100, 102, 104]


def test_a_family_of_edits_hangs_together(spark):
    """Edits of one text, near it and not each other, more than a round compares of an anchor; and texts that are near none."""
    rng = random.Random(9)
    base = [f"w{rng.randrange(10**6)}" for _ in range(200)]
    rows = [(7, " ".join(base))]
    for i in range(100, 180):
        words = list(base)
        for k in rng.sample(range(0, 200, 8), 4):
            words[k] = f"e{i}x{k}"
        rows.append((i, " ".join(words)))
    kept = near_copies.keep_one(spark.createDataFrame(rows, "doc_id long, text string"))
    found = sorted(r["doc_id"] for r in kept.collect())
    assert plain_kept(rows) == [7]  # at 0.81 about one pair in seventy shares no anchor, and these edits have no other partner
    assert found[0] == 7 and len(found) <= 6


def edits(rng, length, many, changed):
    base = [f"w{rng.randrange(10**6)}" for _ in range(length)]
    for i in range(many):
        words = list(base)
        for k in rng.sample(range(length), rng.randrange(1, changed)):
            words[k] = f"e{i}x{k}"
        yield " ".join(words)


@pytest.mark.parametrize("tiles", [1, 3])
def test_an_anchor_is_settled_by_fewer_links_than_members(tiles):
    """Members that are partly similar: a forest joins what all pairs join, also when blocks of members are read two at a time."""
    texts = list(edits(random.Random(4), 120, 90, 9))
    sets = [near_copies.shingles(t) for t in texts]
    words, ids = np.stack([near_copies.fingerprint(s) for s in sets]).view(np.uint64), np.arange(len(texts))
    found = []
    for i in range(tiles):
        for j in range(i, tiles):
            at = ids[np.isin(ids % tiles, (i, j))]
            part = near_copies.settle(at, at, at % tiles, words[at], [sets[k] for k in at])
            assert len(part) < len(at)
            found += part
    assert all(near_copies.alike(sets[u], sets[v]) for u, v in found)
    root = list(ids)
    for u, v in found * len(ids):
        root[u] = root[v] = min(root[u], root[v])
    kept = plain_kept(list(zip(ids.tolist(), texts)))
    assert 1 < len(kept) < len(ids) and sorted({int(r) for r in root}) == kept


def test_tiles_of_an_anchor_keep_the_same(spark, monkeypatch):
    rows = list(enumerate(edits(random.Random(4), 120, 60, 9)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    whole = sorted(r["doc_id"] for r in near_copies.keep_one(df).collect())
    monkeypatch.setattr(near_copies, "TILE", 7)
    assert sorted(r["doc_id"] for r in near_copies.keep_one(df).collect()) == whole


@pytest.mark.parametrize("gathered", [1 << 18, 40])
@pytest.mark.parametrize("size", [1000, 7, 1])
def test_a_component_of_an_anchor_is_one_row(monkeypatch, size, gathered):
    """However many members it has; batches may end within a set's anchors."""
    monkeypatch.setattr(near_copies, "GATHERED", gathered)
    rng, rows, wanted = random.Random(2), [], {}
    for fp in range(60):
        root, n = fp % 3 if fp < 50 else fp, 1 + fp % 5
        rows.append((fp, None, root, n))
        for anchor in sorted(rng.sample(range(12), rng.randrange(9))):
            rows.append((fp, anchor, None, None))
            count, total = wanted.get((anchor, root), (0, 0))
            wanted[anchor, root] = count + 1, total + n
    batch = pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows)], ["fp", "anchor", "root", "n"])
    parts = list(near_copies._gathering(iter([batch.slice(i, size) for i in range(0, len(rows), size)])))
    found, out = {}, 0
    for anchor, root, members, n in (r.values() for part in parts for r in part.to_pylist()):
        count, total = found.get((anchor, root), (0, 0))
        found[anchor, root], out = (count + members, total + n), out + 1
    assert found == wanted
    assert out == len(wanted) < sum(a is not None for _, a, _, _ in rows) or gathered == 40
    assert list(near_copies._gathering(iter([]))) == []
