import hashlib
import random
import re

import numpy as np

from tilemul.llm import licenses, pii, quality

FORMS = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def luhn(digits):
    total = 0
    for i, c in enumerate(reversed(digits)):
        x = int(c) * (2 if i % 2 else 1)
        total += x - 9 if x > 9 else x
    return total % 10 == 0


def brute_pii(text):
    found = []
    for n, (kind, form) in enumerate(FORMS.items()):
        for m in re.finditer(form, text):
            value, digits = m.group(0), re.sub("[^0-9]", "", m.group(0))
            if kind == "ip" and any(int(p) > 255 for p in value.split(".")):
                continue
            if kind == "card" and not (12 <= len(digits) <= 19 and luhn(digits)):
                continue
            if kind == "phone" and not 9 <= len(digits) <= 15:
                continue
            found.append((m.start(), n, m.end(), kind))
    return sorted(found)


def test_base_spans_equal_plain_search(docs_of):
    rng = random.Random(9)
    parts = ["1", "22", "333", "4444", "@", "a.b", "-", " ", ".", "+", "(", ")", "é", "x@y.z", "._q@d.e.f", " 4111 1111 1111 1111", "1.2.3.4", "+1 (234) 555-7777", "\n", "😀"]
    texts = ["".join(rng.choice(parts) for _ in range(rng.randint(0, 30))) for _ in range(500)]
    texts += [None, "", "1" * 20_000, "a." * 20_000 + "@b", "+1" + "(" * 20_000, "a@" + "b." * 5000 + "c", "x@y.zz " * 700, "0" * 4000 + "1.2.3.4"]
    for r in pii.report(docs_of(texts)).collect():
        want = brute_pii(texts[r.doc_id] or "")
        text = ",".join(f"{k}:{s}:{e}" for s, _, e, k in want)
        assert r.base_sha256 == hashlib.sha256(text.encode()).hexdigest()
        assert [r.n_email, r.n_ip, r.n_card, r.n_phone] == [sum(k == kind for *_, k in want) for kind in FORMS]
        spans = r.spans.split(",") if r.spans else []
        assert set(text.split(",") if text else []) <= set(spans)


def test_patterns_discover_and_mask(docs_of):
    stems = [str(400_000_000_000_000 + 7919 * n) for n in range(20)]
    good = [s + next(d for d in "0123456789" if luhn(s + d)) for s in stems]
    texts = [f"please charge card number {c} today and thanks" for c in good] * 2
    texts += ["please charge card number AB12-3456-QX9 today and thanks", "nothing 1234 to see here", "mail me@x.org now"]
    docs = docs_of(texts)
    rows = {r.doc_id: r for r in pii.find(docs).collect()}
    odd = len(texts) - 3
    assert [m.value for m in rows[odd].other] == ["ab12-3456-qx9"] and not rows[odd + 1].spans
    clean = {r.doc_id: r for r in pii.masked(docs).collect()}
    assert clean[odd].text == "please charge card number [OTHER] today and thanks"
    assert clean[odd + 1].text == texts[odd + 1] and clean[odd + 2].text == "mail [EMAIL] now"
    assert clean[odd + 2].n_chars == len("mail [EMAIL] now") and pii.masked(docs).columns == docs.columns
    assert pii.report(docs_of([])).count() == 0 and pii.masked(docs_of([None])).first().text is None


def test_accepted_values_seed_further_rounds(docs_of):
    """Seeds teach a context, its values a shape, the shape's values another context, and that one a word of letters."""
    rng = random.Random(4)
    hexes = lambda: "".join(rng.choice("0123456789abcdef") + rng.choice("abcdef") for _ in range(16)) + "a1"
    texts = [f"x{n} write to customer contact user{n}@mail.org w{n}" for n in range(14)]  # e-mail seeds teach "customer contact"
    texts += [f"x{n} customer contact {hexes()} y{n}" for n in range(6)]  # its values teach a shape of 34 mixed characters
    texts += [f"z{n} ledger entry: {hexes()} q{n}" for n in range(20)]  # the shape's values teach "entry :"
    texts += ["at last ledger entry: swordfish ended", "a plain entry about swordfish", "in 2021 and 2022 we sold 12345 cars"]
    rows = {r.doc_id: r for r in pii.find(docs_of(texts)).collect()}
    found = lambda n: [m.value for m in rows[n].other]
    assert all(len(found(n)) == 1 and len(found(n)[0]) == 34 for n in range(14, 40))
    assert found(40) == ["swordfish"] and not rows[41].spans and not rows[42].spans


def test_cued_values_and_refused_cards(docs_of):
    rng = random.Random(2)
    cards = ["".join(rng.choice("0123456789") for _ in range(16)) for _ in range(200)]
    texts = [f"note {c} ends" for c in cards]
    texts += ['set TOKEN = "9f8e7d6c5b4a39281706" here', "the token = next one", None, ""]
    rows = {r.doc_id: r for r in pii.find(docs_of(texts)).collect()}
    for n, c in enumerate(cards):  # one in ten passes the check, and these teach the shape of all
        assert [m.value for m in (rows[n].card if luhn(c) else rows[n].other)] == [c]
    assert [m.value for m in rows[200].other] == ["9f8e7d6c5b4a39281706"] and not rows[201].spans
    clean = {r.doc_id: r.text for r in pii.masked(docs_of(texts)).collect()}
    assert clean[200] == 'set TOKEN = "[OTHER]" here' and clean[202] is None


def brute_scores(edges, seeds):
    """Rounds over a pattern-value graph held in memory."""
    score = {v: float(v in seeds) for _, v in edges}
    while True:
        conf = {}
        for p in {p for p, _ in edges}:
            values = [v for q, v in edges if q == p]
            known = [score[v] for v in values if score[v] > 0]
            if len(known) >= pii.SUPPORT:
                c = sum(known) / (sum(known) + pii.UNKNOWN[p[0]] * (len(values) - len(known)))
                if c >= pii.CONFIDENT:
                    conf[p] = c
        fresh = {}
        for v in score:
            doubt = np.prod([1 - conf[p] if conf[p] < 1 else 1e-9 for p, w in edges if w == v and p in conf])
            fresh[v] = score[v] or (1 - doubt if 1 - doubt >= pii.TAKEN else 0.0)
        if {v for v in fresh if fresh[v]} == {v for v in score if score[v]}:
            return fresh
        score = fresh


def test_graph_scores_equal_brute_force(docs_of):
    rng = random.Random(12)
    values = [f"id{n}@ab.cd" if n < 50 else f"code{n}-77{n}" for n in range(80)]
    contexts = [("red fox", "ran"), ("old owl", "sat"), ("big dog", "lay"), ("new cat", "hid")]
    texts = []
    for n, v in enumerate(values):
        for c in rng.sample(contexts, 2):
            if n >= 50 and rng.random() < 0.5:
                texts.append(f"{n}x some other words {v} end{n}")
            else:
                texts.append(f"{c[0]} {v} {c[1]}")
    based = pii.with_instances(docs_of(texts))
    some = pii.instances(based).collect()
    edges = {(p, r.value) for r in some for p in r.patterns}
    want = brute_scores(edges, {r.value for r in some if r.seed})
    got = {r.value: r.score for r in pii.discover(based).collect()}
    assert {v for v, s in want.items() if s and not v.startswith("id")} == set(got) and len(got) > 3
    assert all(abs(want[v] - s) < 1e-9 for v, s in got.items())


def test_native_plan(docs_of):
    plan = pii.report(docs_of(["a@b.cc"]))._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


def test_license_rules_and_suppression():
    rules = licenses.build_rules()
    assert len(rules) > 400 and len(licenses.SIGNATURES) > 100 and [r.priority for r in rules] == sorted((r.priority for r in rules), reverse=True)
    s = licenses.Scanner()
    label = lambda t: {d.label for d in s.detections(t.lower())}
    assert label("Licensed under the Apache License, Version 2.0.") == {"apache"}
    assert label("under CC BY-NC 4.0.") == {"cc-by-nc"}
    assert label("SPDX-License-Identifier: LGPL-2.1-or-later") == {"lgpl"}
    assert label("GNU Lesser General Public License version 3") == {"lgpl"}
    assert label("Permission is hereby granted, free of charge, to any person obtaining a copy") == {"mit"}
    assert label("an ordinary sentence about licences of taste") == set()
    assert label("released under the gnu gpl version 3") == {"gpl"} and label("gnu lgpl 2.1") == {"lgpl"}
    assert label("expat license") == {"mit"} and label("psf license 2") == {"python"}
    assert label("gnu general\npublic license version 2") == {"gpl"} and label("# CC-BY\n# SA 4.0") == {"cc-by-sa"}
    assert label("This source code form is subject to\n * the terms of the Mozilla Public\n * License, v. 2.0") == {"mpl"}
    assert label("Redistributions of source code must retain the above copyright notice, this list\n// of conditions and the following disclaimer.") == {"bsd"}
    # a detection stands unless one of higher priority, or a longer equal one, holds it
    rng = random.Random(1)
    for _ in range(200):
        found = [licenses.Detection(a, a + rng.randint(1, 9), rng.choice("xy"), rng.choice([1, 2, 3])) for a in (rng.randint(0, 20) for _ in range(7))]
        kept = licenses.suppressed(found)
        assert set(kept) <= set(found)
        inside = lambda d, k: k.start <= d.start and d.end <= k.end
        for d in found:
            held = any(inside(d, k) and (k.priority > d.priority or (k.priority == d.priority and (k.start, k.end) != (d.start, d.end))) for k in found)
            assert (d in kept) or held
            if d in kept:
                assert not any(inside(d, k) and k.priority > d.priority for k in kept)


def sample(node, rng):
    """A text that a parsed pattern matches, assertions aside."""
    from re import _constants as c

    out = ""
    for op, arg in node:
        if op is c.LITERAL:
            out += chr(arg)
        elif op is c.NOT_LITERAL or op is c.ANY:
            out += "x"
        elif op is c.IN:
            if arg[0][0] is c.NEGATE:
                out += "x"
                continue
            kind, value = rng.choice(arg)
            out += chr(value) if kind is c.LITERAL else chr(rng.randint(*value)) if kind is c.RANGE else "x"
        elif op in (c.MAX_REPEAT, c.MIN_REPEAT):
            low, high, part = arg
            out += "".join(sample(part, rng) for _ in range(rng.randint(low, min(high, low + 2))))
        elif op is c.SUBPATTERN:
            out += sample(arg[3], rng)
        elif op is c.BRANCH:
            out += sample(rng.choice(arg[1]), rng)
    return out


def test_keywords_hide_no_detection():
    from re import _parser

    rng = random.Random(3)
    gated, plain = licenses.Scanner(), licenses.Scanner(gated=False)
    for n, rule in enumerate(gated.rules):
        hits = 0
        for _ in range(12):
            text = sample(_parser.parse(rule.pattern), rng)
            if re.search(rule.pattern, text):
                hits += 1
                assert n in gated.asked(text), (rule, text)
        assert hits, rule
    for _ in range(60):
        some = rng.sample(gated.rules, 3)
        text = " and ".join(sample(_parser.parse(r.pattern), rng) for r in some)
        assert gated.detections(text) == plain.detections(text)


def test_license_edges(docs_of):
    assert licenses.scan(docs_of([])).count() == 0
    rows = licenses.scan(docs_of(["under the MIT License"] * 3, [1, 1, None])).collect()
    assert [(r.base_labels, r.labels, r.score) for r in rows] == [("mit", "mit", 0.4)] * 3


def brute_words(text):
    lowered = re.sub("[A-Z]", lambda m: m.group(0).lower(), text)
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lowered)


def test_license_base(docs_of):
    rng = random.Random(6)
    parts = ["GNU", "general", "public", "license", "Apache", "cc", "by", "MIT", "é", "-", "(", "x9", "cc-by", "Kelvin\u212a"]
    texts = [" ".join(rng.choice(parts) for _ in range(rng.randint(0, 40))) for _ in range(300)] + [None, "", "a" * 100_000, "CC BY"]
    phrases = {tuple(p.split()): v for p, v in licenses.PHRASES.items()}
    for r in licenses.scan(docs_of(texts)).collect():
        words = brute_words(texts[r.doc_id] or "")
        places = sorted((i, v) for p, v in phrases.items() for i in range(len(words)) if tuple(words[i : i + len(p)]) == p)
        assert (r.n_words, r.n_base) == (len(words), len(places))
        assert (r.first_word, r.last_word) == ((places[0][0], places[-1][0]) if places else (None, None))
        assert r.base_labels == ",".join(sorted({v for _, v in places}))
        assert set(filter(None, r.base_labels.split(","))) <= set(r.labels.split(","))
        assert 0 <= r.score <= 1


def test_contexts_equal_brute_force():
    rng = np.random.default_rng(3)
    docs = [rng.integers(0, 50, n).astype(np.uint32) for n in (0, 1, 2, 30, 7)]
    index = quality.index_vectors()
    total = np.zeros((quality.BUCKETS, quality.DIM), np.int64)
    quality.add_contexts(total, docs, index)
    want = np.zeros_like(total)
    for d in docs:
        for i, w in enumerate(d):
            for j in range(max(0, i - quality.REACH), min(len(d), i + quality.REACH + 1)):
                if i != j:
                    want[w] += index[d[j]]
    assert (total == want).all()


def test_quality_held_out_accuracy(spark):
    d = "/root/testdata/sf0.01"
    docs, labels = (spark.read.parquet(f"{d}/{t}.parquet") for t in ("documents", "labels"))
    model = quality.fit(docs, labels)
    rows = quality.score(docs, model).join(labels, "doc_id").where("held_out").toPandas()
    assert (rows.predicted == rows.quality).mean() > 0.95
    again = quality.fit(docs.repartition(7), labels.repartition(3))
    assert np.allclose(again.network.w1, model.network.w1)


def test_quality_edges(docs_of, spark):
    labels = spark.createDataFrame([(0, 1), (1, 0), (2, None), (None, 1)], "doc_id long, quality int")
    model = quality.fit(docs_of(["good words", "$$$ !!!", None, ""]), labels)
    rows = quality.score(docs_of([None, "", "x"], [1, None, 3]), model).collect()
    assert len(rows) == 3 and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in rows)
    assert quality.score(docs_of([]), model).count() == 0
    none = quality.fit(docs_of(["a"]), labels.limit(0))
    assert quality.score(docs_of(["a"]), none).first().score == 0.5
    held = {r.doc_id: r.held_out for r in quality.score(docs_of(["x"] * 30), model).collect()}
    import zlib

    assert held == {i: zlib.crc32(str(i).encode()) % 3 == 1 for i in range(30)}
    for t in (0.5, 3.0):
        z = np.random.default_rng(0).normal(0, 4, 4000)
        y = (np.random.default_rng(1).random(4000) < 1 / (1 + np.exp(-z / t))).astype(float)
        assert abs(quality.fit_temperature(z, y) - t) < 0.3 * t
    assert docs_of(["a"]).columns == quality.keep_good(docs_of(["a"]), none).columns
