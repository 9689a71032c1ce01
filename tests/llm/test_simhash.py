import numpy as np
import xxhash

from tilemul.llm import simhash


def brute_fingerprint(text):
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    grams = [b" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or [b" ".join(words)]
    hashes = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute_components(values, most=3):
    n = len(values)
    parent = list(range(n))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(n):
        for j in range(i):
            if bin(values[i] ^ values[j]).count("1") <= most:
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    return [find(i) for i in range(n)]


def test_fingerprints_and_components(spark, docs_of):
    rng = np.random.default_rng(2)
    base = [" ".join(rng.choice(["alpha", "beta", "gamma", "DELTA", "é\u00e9", "x"], 120)) for _ in range(6)]
    texts = ["", None, "one", "one two", "ONE two", "a\tb\nc d"]
    for b in base:
        words = b.split()
        for n in range(4):
            words = words[:]
            words[n * 7] = "changed"
            texts += [" ".join(words)]
        texts += [b, b]
    texts.append("word " * 70_000)
    want = [brute_fingerprint(t) for t in texts]
    rows = {r.doc_id: r for r in simhash.near_duplicates(docs_of(texts)).collect()}
    assert [int(rows[i].fingerprint, 16) for i in range(len(texts))] == want
    assert [rows[i].component_id for i in range(len(texts))] == brute_components(want)


def neighbours(rng, n):
    """Values in chains and balls, with shared halves."""
    out = set()
    while len(out) < n:
        x = int(rng.integers(0, 1 << 63)) * 2 + int(rng.integers(0, 2))
        for _ in range(int(rng.integers(1, 12))):
            out.add(x)
            for bit in rng.choice(64, int(rng.integers(1, 5)), replace=False).tolist():
                x ^= 1 << bit
    return sorted(out)


def test_links_are_complete_and_hot_segments_lose_none(spark):
    rng = np.random.default_rng(5)
    values = neighbours(rng, 150)
    half = int(rng.integers(0, 1 << 32)) << 32
    values += [half | int(v) for v in rng.integers(0, 1 << 12, 60)]  # one shared half, near each other
    values = sorted(set(values))
    signed = np.array(values, dtype=np.uint64).view(np.int64).tolist()
    df = spark.createDataFrame([(v,) for v in signed], "fp long")
    want = {
        (min(a, b), max(a, b)) for n, a in enumerate(signed) for b in signed[:n]
        if bin((a ^ b) & (1 << 64) - 1).count("1") <= 3
    }
    assert {tuple(r) for r in simhash.links(df).collect()} == want
    order = {v: n for n, v in enumerate(values)}
    for most in (1, 2, 3):
        roots = brute_components(values, most)
        groups = {}
        for v, r in zip(values, roots):
            groups.setdefault(r, set()).add(v)
        for hot in (1024, 4, 1):
            found = {}
            for r in simhash.components(simhash.links(df, most, hot)).collect():
                found.setdefault(r.root, set()).add(r.node & (1 << 64) - 1)
            got = sorted(sorted(map(order.get, g)) for g in found.values())
            assert got == sorted(sorted(map(order.get, g)) for g in groups.values() if len(g) > 1), (most, hot)


def test_long_chain(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(300)], "a long, b long")
    roots = simhash.components(edges).collect()
    assert len(roots) == 301 and {r.root for r in roots} == {0}


def test_edges(docs_of):
    assert simhash.near_duplicates(docs_of([])).count() == 0
    rows = simhash.near_duplicates(docs_of(["a b c d", "a b c d", "a b c d"], [4, 4, None])).collect()
    assert [r.component_id for r in rows] == [4, 4, 4]
    kept = simhash.keep_one(docs_of(["p q r s", "p q r s", "other words stand here now", None, ""], [7, 3, 5, 6, 8]))
    assert sorted(r.doc_id for r in kept.collect()) == [3, 5, 6] and "size" in kept.columns


def test_keep_one_tells_rows_without_or_with_repeated_ids_apart(docs_of):
    from tilemul.llm import nearcopies

    words = [" ".join(f"{stem}{n}" for n in range(9)) for stem in "abcde"]
    texts = [words[0], words[0], words[1], words[1], words[2], words[3], words[4], words[4]]
    rows = docs_of(texts, [None, 5, None, 9, None, 7, 7, 7])
    want = sorted([(5, words[0]), (9, words[1]), (-1, words[2]), (7, words[3]), (7, words[4])])
    for keep in (simhash.keep_one, nearcopies.keep_one):
        assert sorted((-1 if r.doc_id is None else r.doc_id, r.text) for r in keep(rows).collect()) == want
