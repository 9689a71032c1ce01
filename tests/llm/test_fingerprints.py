import hashlib

import numpy as np
import pytest

from tilemul.llm import fingerprints as fp


def brute(text, k, window):
    """Chosen (position) set from the definition, over gram hashes."""
    hashes = fp.gram_hashes(fp.code_points(text), k).tolist()
    if not hashes:
        return []
    w = min(window, len(hashes))
    chosen = set()
    for at in range(len(hashes) - w + 1):
        part = hashes[at : at + w]
        low = min(part)
        chosen.add(at + max(i for i, h in enumerate(part) if h == low))
    return sorted(chosen)


@pytest.mark.parametrize("k,window", [(1, 1), (3, 4), (5, 7), (24, 40), (2, 8), (6, 16)])
def test_windows_minimum_rightmost(k, window):
    rng = np.random.default_rng(k * 100 + window)
    for n in (0, 1, 2, 5, 30, 200):
        text = "".join(rng.choice(list("abé😀"), n))
        _, positions = fp.winnow(fp.code_points(text), k, window)
        assert positions.tolist() == brute(text, k, window)
    assert fp.winnow(fp.code_points("a" * 300), k, window)[1].tolist() == brute("a" * 300, k, window)


def test_gram_hashes_depend_on_the_gram_only():
    text = "the quick brown fox jumps over the quick brown dog"
    for k in (1, 3, 7, 15, 16):
        h = fp.gram_hashes(fp.code_points(text), k).tolist()
        grams = [text[i : i + k] for i in range(len(text) - k + 1)]
        assert len(h) == len(grams) and len(set(zip(grams, h))) == len(set(grams)) == len(set(h))


def test_match_guarantee():
    rng = np.random.default_rng(1)
    shared = "".join(rng.choice(list("abcdefgh "), fp.K_GRAM + fp.WINDOW - 1))
    for _ in range(20):
        a, b = ("".join(rng.choice(list("ijklmnop "), 300)) for _ in range(2))
        x = fp.winnow(fp.code_points(a[:100] + shared + a[100:]))[0]
        y = fp.winnow(fp.code_points(b[:37] + shared + b[37:]))[0]
        assert set(x.tolist()) & set(y.tolist())


@pytest.mark.parametrize("rows_per_range", [1, 2, 1000])
def test_edited_texts(docs_of, rows_per_range):
    texts = ["", None, "a", "é" * 40, "😀bc" * 300, "same text here", "same text here", "x y z " * 50, "q", "long " * 5000]
    ids = [5, 9, -3, 100, 7, 8, 2, 11, 50, 1]
    rows = {r.doc_id: r for r in fp.compare_with_edits(docs_of(texts, ids), rows_per_range=rows_per_range).collect()}
    order = sorted(range(len(ids)), key=lambda n: -ids[n])
    assert len(rows) == len(ids)
    for at, n in enumerate(order):
        own, following = texts[n] or "", texts[order[(at + 1) % len(order)]] or ""
        half = len(own) // 2
        edited = own[: len(own) - half] + following[:half]
        r = rows[ids[n]]
        assert r.n_chars == len(own)
        assert r.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        x, y, z = (fp.winnow(fp.code_points(t))[0] for t in (own, edited, following))
        assert r.fingerprint == fp.spelled(x) and r.edited_fingerprint == fp.spelled(y)
        assert r.positions == brute(own, fp.K_GRAM, fp.WINDOW) and r.edited_positions == brute(edited, fp.K_GRAM, fp.WINDOW)
        assert r.near_edited == fp.likeness(x, y) and r.near_next == fp.likeness(x, z)


def test_edge_tables(docs_of):
    assert fp.compare_with_edits(docs_of([])).count() == 0
    one = fp.compare_with_edits(docs_of(["only document"])).first()
    assert one.near_next == 1.0
    repeated = fp.compare_with_edits(docs_of(["a b", "a b", None], [1, 1, None]), rows_per_range=1).collect()
    assert len(repeated) == 3
    kept = fp.fingerprints(docs_of(["abc", None])).collect()
    assert [len(r.hashes) for r in kept] == [1, 0] and kept[0].positions == [0]
