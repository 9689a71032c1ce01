import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from tilemul.llm import mixing, packing

TEXTS = ["", None, "hello world", "Árbol de la vida\n\n two  spaces", "日本語 text <|endoftext|> here", "word " * 3000, "don't we'll 123", "x" * 5000]


def test_encoder_equals_tokenizers():
    from tokenizers import Tokenizer

    path = packing.default_tokenizer()
    mine, theirs = packing.Encoder(path), Tokenizer.from_file(path)
    assert mine.fast is not None
    rng = np.random.default_rng(4)
    letters = list("ab C1 2'\n\t  .,é$#_ñÜß'sll") + ["\x85", "日", "<|endoftext|>", "\u00ad", "ǅ", "²"]
    for text in [t or "" for t in TEXTS] + ["".join(rng.choice(letters, n)) for n in range(150)]:
        assert mine.ids(text).tolist() == theirs.encode(text, add_special_tokens=False).ids


def test_pieces_and_packing(docs_of):
    docs = docs_of(TEXTS * 3)
    rows = packing.pack(packing.pieces(docs), pieces_per_partition=7).collect()
    encoder = packing.Encoder(packing.default_tokenizer())
    by_doc, by_sequence = {}, {}
    for r in rows:
        by_doc.setdefault(r.doc_id, []).append(r)
        by_sequence.setdefault(r.sequence_id, []).append(r)
    for i, text in enumerate(TEXTS * 3):
        ids = np.append(encoder.ids(text or ""), np.uint32(2)).astype("<u4")
        at = 0
        for n, r in enumerate(sorted(by_doc[i], key=lambda r: r.piece)):
            assert (r.piece, r.start) == (n, at) and (n == 0 or r.length == 1024)
            assert bytes(r.ids) == ids[at : at + r.length].tobytes()
            at += r.length
        assert at == len(ids)
    for part in by_sequence.values():
        end = 0
        for r in sorted(part, key=lambda r: r.offset):
            assert r.offset == end
            end += r.length
        assert end <= 1024
    best = -(-sum(r.length for r in rows) // 1024)
    assert best <= len(by_sequence) <= best + 2
    digests = packing.pieces(docs).select("ids", packing.crc_of_ids()).collect()
    assert all(r.ids_crc32 == zlib.crc32(bytes(r.ids)) for r in digests)


def test_partitions_exchange_and_certify(spark):
    rng = np.random.default_rng(11)
    lengths = [int(n) for n in np.minimum(1024, rng.gamma(0.8, 300, 6000) + 1)]
    some = spark.createDataFrame([(n,) for n in lengths], "length long")
    rows = packing.pack(some, pieces_per_partition=400).collect()
    assert sorted(r.length for r in rows) == sorted(lengths)
    count = len({r.sequence_id for r in rows})
    bound = packing.lower_bound(np.bincount(lengths, minlength=1025))
    assert bound <= count <= bound + 2
    parts = {}
    for r in rows:
        if r.length < 1024:
            parts.setdefault((r["round"], r.sequence_id >> 27), []).append(r)
    assert {k[0] for k in parts} >= {0, 1} and len([k for k in parts if k[0] == 0]) >= 10
    for some_rows in parts.values():  # settled bins are among the partition's, the certificate holds for it
        assert len({(r.part_bins, r.part_bound) for r in some_rows}) == 1
        assert len({r.sequence_id for r in some_rows}) <= some_rows[0].part_bins >= some_rows[0].part_bound
    # what partitions alone would need, without any exchange, is more
    alone = packing.pack(some, pieces_per_partition=400, rounds=1).select("sequence_id").distinct().count()
    assert alone >= count + 5


def test_bounds_and_best_fit():
    rng = np.random.default_rng(0)
    for _ in range(40):
        lengths = rng.integers(1, 25, rng.integers(1, 60))
        bins, offsets, rooms = packing.best_fit_decreasing(lengths, 24)
        used = np.bincount(bins, lengths)
        assert (used + rooms == 24).all() and used.max() <= 24
        bound = packing.lower_bound(np.bincount(lengths, minlength=25), 24)
        assert -(-lengths.sum() // 24) <= bound <= len(rooms)
    halves = np.full(9, 13)
    assert packing.lower_bound(np.bincount(halves, minlength=25), 24) == 9
    thirds = np.array([9] * 10)  # two to a bin, by the rounded function
    assert packing.lower_bound(np.bincount(thirds, minlength=25), 24) == 5


def test_empty_packing(docs_of):
    assert packing.pack(packing.pieces(docs_of([]))).count() == 0


def brute_targets(sizes, weights, share, most):
    got = [0.0] * len(sizes)
    free, left = set(range(len(sizes))), share * sum(sizes)
    while free and left > 1e-9:
        total = sum(weights[i % 3] for i in free)
        over = [i for i in free if left * weights[i % 3] / total > most * sizes[i]]
        if not over:
            for i in free:
                got[i] = left * weights[i % 3] / total
            break
        for i in over:
            got[i] = most * sizes[i]
        free -= set(over)
        left = share * sum(sizes) - sum(got)
    return got


@pytest.mark.parametrize("sizes", [[10, 20, 30], [1, 1, 1000, 5, 0], [100], [], [0, 0], [7] * 9])
def test_targets(sizes):
    assert mixing.targets(sizes) == pytest.approx(brute_targets(sizes, (5, 2, 1), 1.5, 2))


def test_split_quotas():
    quotas = np.array([1000, 3, 0, 517])
    parts = mixing.split_quotas(quotas, 7)
    assert (parts.sum(axis=0) == quotas).all() and parts.sum(axis=1).max() - parts.sum(axis=1).min() <= 3
    assert (parts == mixing.split_quotas(quotas, 7)).all()


def test_mix(docs_of):
    rng = np.random.default_rng(3)
    texts = [None if n == 3 else "" if n == 4 else " ".join(["w"] * int(rng.integers(1, 90))) for n in range(300)]
    sources = [None if n % 11 == 0 else "aä"[n % 2] if n % 3 else "é" for n in range(300)]
    docs = docs_of(texts, sources=sources)
    rows = mixing.taken_words(docs, block=16).collect()
    assert sorted(map(tuple, rows)) == sorted(map(tuple, mixing.taken_words(docs, block=16).collect()))
    assert len(rows) == 300
    by_source = {}
    for r in rows:
        assert r.size == len((texts[r.doc_id] or "").split()) and 0 <= r.taken <= 2 * r.size
        by_source.setdefault(sources[r.doc_id], []).append(r)
    order = sorted((s for s in by_source if s is not None), key=lambda s: s.encode()) + [None]
    want = mixing.targets([by_source[s][0].source_size for s in order])
    for s, t in zip(order, want):
        mine = by_source[s]
        assert mine[0].source_size == sum(r.size for r in mine) and mine[0].target == pytest.approx(t)
        assert abs(sum(r.taken for r in mine) - t) <= 1
    plan = mixing.plan(docs, block=16)
    drawn = mixing.with_draws(docs.select("doc_id", "text", "source"), plan).collect()
    per_doc = {r.doc_id: sum(d.words for d in r.draws) for r in drawn}
    assert per_doc == {r.doc_id: r.taken for r in rows}
    # the tree decides: per source and shard the blocks drawn are those between the shard's ends
    ends = {r.source_no: (r.ends, r.quota, r.blocks, r.passes) for r in plan.sources.collect()}
    by_shard = {}
    for r in drawn:
        e, _, blocks, passes = ends[r.source_no]
        for d in r.draws:
            by_shard.setdefault((r.source_no, d.shard), set()).add((d["pass"], r.block))
    for (s, shard), drawn_blocks in by_shard.items():
        e = ends[s][0]
        assert len(drawn_blocks) <= e[shard] - (e[shard - 1] if shard else 0)
    for s, (e, quota, blocks, passes) in ends.items():
        assert e[-1] == quota and passes * blocks <= quota <= (passes + 1) * blocks
    sizes = np.diff(np.array([[0, *e] for e, *_ in ends.values()]), axis=1).sum(axis=0)
    assert sizes.max() - sizes.min() <= 4  # shards of even size
    mixed = mixing.mixed(docs, block=16)
    assert mixed.columns == docs.columns
    lengths = {}
    for r in mixed.collect():
        lengths[r.doc_id] = lengths.get(r.doc_id, 0) + len(r.text.split())
    assert lengths == {i: n for i, n in per_doc.items() if n}
    assert mixing.taken_words(docs_of([])).count() == 0 and mixing.mixed(docs_of([])).count() == 0


def test_without_the_tree_nothing_is_taken(docs_of, monkeypatch):
    docs = docs_of(["a b c d"] * 5 + ["e f"] * 40, sources=["x"] * 20 + ["y"] * 25)
    assert mixing.mixed(docs).count()
    monkeypatch.setattr(mixing, "split_quotas", lambda quotas, shards, seed: np.zeros((shards, len(quotas)), np.int64))
    assert mixing.mixed(docs).count() == 0


def test_mix_of_repeated_rows_and_clashing_ids(docs_of, spark):
    rows = docs_of(["a b c"] * 2, [1, 1], ["x", "y"])
    want = {r.source: r for r in spark.createDataFrame([("x", 6.0), ("y", 3.0)], "source string, target double").collect()}
    plan = mixing.taken_words(rows).collect()
    assert sorted((r.size, r.source_size, r.target, r.taken) for r in plan) == sorted((3, 3, t.target, int(t.target)) for t in want.values())
    got = mixing.mixed(rows).collect()
    assert sorted((r.doc_id, r.text, r.source) for r in got) == [(1, "a b c", "x"), (1, "a b c", "x"), (1, "a b c", "y")]
    # copies in one block share what is left evenly
    many = docs_of(["w " * 10] * 30 + ["v " * 10] * 30, [7] * 30 + list(range(100, 130)), ["x"] * 30 + ["y"] * 30)
    taken = {}
    for r in mixing.taken_words(many, block=8).collect():
        taken.setdefault(r.doc_id, []).append(r)
    assert len({r.taken for r in taken[7]}) == 1 and abs(sum(r.taken for r in taken[7]) - taken[7][0].target) < 30
    total = sum(len(r.text.split()) for r in mixing.mixed(many, block=8).collect())
    assert total == sum(r.taken for rs in taken.values() for r in rs)


def test_many_sources_without_broadcast(docs_of, monkeypatch):
    texts = [" ".join(["w"] * (n % 17 + 1)) for n in range(200)]
    docs = docs_of(texts, sources=[None if n % 50 == 0 else f"s{n % 40:02d}" for n in range(200)])
    want = sorted(map(tuple, mixing.taken_words(docs, block=4).collect()))
    monkeypatch.setattr(mixing, "BROADCAST_ROWS", 0)
    monkeypatch.setattr(mixing, "CHUNK", 2)
    assert sorted(map(tuple, mixing.taken_words(docs, block=4).collect())) == want
    sizes = {}
    for n, t in enumerate(texts):
        s = None if n % 50 == 0 else f"s{n % 40:02d}"
        sizes[s] = sizes.get(s, 0) + len(t.split())
    order = sorted(s for s in sizes if s is not None) + [None]
    targets = dict(zip(order, brute_targets([sizes[s] for s in order], (5, 2, 1), 1.5, 2)))
    for r in mixing.with_draws(docs.select("doc_id", "text", "source"), mixing.plan(docs, block=4)).collect():
        assert r.target == pytest.approx(targets[r.source])
