import numpy as np

from tilemul.llm import nearcopies, simhash


def brute_similar(a, b):
    grams = lambda t: {tuple(t.lower().split()[i : i + 5]) for i in range(len(t.split()) - 4)}
    x, y = grams(a), grams(b)
    return 5 * len(x & y) >= 4 * len(x | y)


def brute_kept(texts):
    parent = list(range(len(texts)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(texts)):
        for j in range(i):
            if brute_similar(texts[i], texts[j]):
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    return sorted({find(i) for i in range(len(texts))})


def test_near_copies_equal_brute_force(docs_of):
    rng = np.random.default_rng(8)
    texts = []
    for _ in range(12):
        words = [f"w{x}" for x in rng.integers(0, 3000, 200)]
        texts.append(" ".join(words))
        for edits in (1, 2, 3, 4, 5, 8, 20):
            some = words[:]
            for at in rng.choice(200, edits, replace=False).tolist():
                some[at] = "edited"
            texts.append(" ".join(some))
    pairs = [(a, b) for a in texts for b in texts if a < b and brute_similar(a, b)]
    # pairs that three bits of a fingerprint do not link
    assert any((simhash.fingerprint(a) ^ simhash.fingerprint(b)).bit_count() > 3 for a, b in pairs)
    kept = sorted(r.doc_id for r in nearcopies.keep_one(docs_of(texts)).collect())
    assert kept == brute_kept(texts)


def test_crowded_bands_lose_nothing(docs_of):
    """Texts around one common passage, some of them near copies of each other."""
    rng = np.random.default_rng(3)
    passage = [f"p{n}" for n in range(120)]
    texts = []
    for n in range(40):
        own = [f"o{n}x{k}" for k in range(60)]
        texts.append(" ".join(own[:30] + passage + own[30:]))
        if n % 3 == 0:
            own[int(rng.integers(0, 60))] = "other"
            texts.append(" ".join(own[:30] + passage + own[30:]))
    docs, want = docs_of(texts), brute_kept(texts)
    assert len(want) == 40
    for hot_band in (nearcopies.HOT_BAND, 3, 1):
        found = nearcopies.near_copies(docs, hot_band).groupBy("component").agg({"doc_id": "min"}).collect()
        assert sorted(r[1] for r in found) == want


def test_stage_drops_near_copies_with_wide_fingerprints(spark, docs_of):
    import corpus_pipeline

    words = [f"w{n}" for n in range(120)]
    for seed in range(100):  # a text whose copy is similar and more than three bits away
        base = [f"{w}x{seed}" for w in words]
        copy = base[:]
        copy[30], copy[90] = "other", "another"
        if (simhash.fingerprint(" ".join(base)) ^ simhash.fingerprint(" ".join(copy))).bit_count() > 3:
            break
    texts = [" ".join(base), " ".join(copy), "something else stands in this text", "short", "Short ", None, ""]
    kept = corpus_pipeline.near_dedup(spark, docs_of(texts), "")
    assert sorted(r.doc_id for r in kept.collect()) == [0, 2, 3, 5]


def test_fingerprints_link_before_bands(spark, docs_of, monkeypatch):
    """The method's own step stands in the stage: without bands it still links what is within three bits."""
    words = [f"v{n}" for n in range(400)]
    copy = words[:]
    copy[399] = "other"
    texts = [" ".join(words), " ".join(copy), " ".join(f"z{n}" for n in range(400))]
    prints = [nearcopies.print_of(nearcopies.shingles(nearcopies.words_of(t))) for t in texts]
    assert ((prints[0] ^ prints[1]) & (2**64 - 1)).bit_count() <= 3
    monkeypatch.setattr(nearcopies, "bands", lambda found: np.zeros(0, np.int64))
    assert sorted(r.doc_id for r in nearcopies.keep_one(docs_of(texts)).collect()) == [0, 2]


def test_few_links_are_followed_without_rounds_of_joins(docs_of, monkeypatch):
    rng = np.random.default_rng(5)
    texts = []
    for n in range(4):
        words = [f"g{n}x{k}" for k in range(120)]
        texts.append(" ".join(words))
        for edits in (1, 2, 3, 4):
            some = words[:]
            for at in rng.choice(120, edits, replace=False).tolist():
                some[at] = "edited"
            texts.append(" ".join(some))
    want = brute_kept(texts)
    with monkeypatch.context() as m:
        m.setattr(nearcopies, "FEW_LINKS", 0)  # all links go through star contraction
        assert sorted(r.doc_id for r in nearcopies.keep_one(docs_of(texts)).collect()) == want

    def no_rounds(*_):
        raise AssertionError("few links went through star contraction")

    monkeypatch.setattr(nearcopies, "components", no_rounds)
    assert sorted(r.doc_id for r in nearcopies.keep_one(docs_of(texts)).collect()) == want
