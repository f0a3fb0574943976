"""Line, substring and near-duplicate removal, language, personal data and packing on small fixtures."""

from __future__ import annotations

import hashlib
import random
import re
from itertools import combinations

import numpy as np
import pytest

from nearfield.llm import language, lines, neardup, packing, private, repeats
from nearfield.llm.common import folded_words_of
from nearfield.llm.shingles import shingle_set

WORDS = [f"w{i}" for i in range(400)]


def prose(rng, n):
    return " ".join(rng.choice(WORDS) for _ in range(n))


# lines


def test_lines_by_brute_force_with_nulls_ties_and_clashing_columns(spark, documents):
    rows = [(i, f"own {i}\n  Common Line \nrest {i % 12}\n\n") for i in range(30)] + [(100, None), (101, ""), (102, "COMMON line"), (None, "common line\nx")]
    docs = documents(rows).withColumnRenamed("n_chars", "n_lines")
    cut = {r.doc_id: r for r in lines.drop_common_lines(docs).collect()}
    assert cut[3].text == "own 3\nrest 3\n\n" and (cut[3].n_lines, cut[3].n_dropped) == (5, 1)
    assert (cut[100].text, cut[100].n_lines) == ("", 1) and (cut[101].text, cut[101].n_lines) == ("", 1)
    assert (cut[102].text, cut[102].n_dropped) == ("", 1) and cut[None].text == "x"
    assert lines.drop_common_lines(docs.limit(0)).count() == 0


def test_repeated_rows_count_as_one_document(spark, documents):
    nine = documents([(i, "same") for i in range(9)] + [(0, "same")] * 5)
    assert {r.n_dropped for r in lines.drop_common_lines(nine).collect()} == {0}
    assert lines.drop_common_lines(nine).count() == 14
    ten = documents([(i, "same") for i in range(10)])
    assert {r.n_dropped for r in lines.drop_common_lines(ten).collect()} == {1}


# substrings


@pytest.mark.parametrize("window", [5, 13, 50])
def test_repeats_by_brute_force(spark, documents, window):
    rng = random.Random(window)
    shared = [prose(rng, n) for n in (window, window + 1, 3 * window, window - 1)]
    rows = [(i, " ".join(x for _ in range(3) for x in (prose(rng, rng.randrange(0, 40)), rng.choice(shared)))) for i in range(60)] + [(200, None), (201, ""), (202, "a b"), (203, shared[2]), (204, shared[2])]
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in repeats.digest(repeats.cut_repeats(documents(rows), window)).collect()}
    assert got == repeats.brute_force(dict(rows), window)


def test_repeats_defined_cases(spark, documents):
    text = prose(random.Random(1), 20)
    twice = documents([(1, text), (1, text), (2, text), (None, text)])
    got = sorted(((r.doc_id or 0, r.n_removed) for r in repeats.cut_repeats(twice).collect()))
    assert got == [(0, 0), (1, 0), (1, 0), (2, 20)]
    assert repeats.cut_repeats(documents([])).count() == 0


def test_levels_go_on_until_no_candidate_survives(spark, documents):
    rng = random.Random(2)
    long_, short = prose(rng, 120), prose(rng, 20)
    docs = documents([(1, f"{long_} x"), (2, f"y {long_}"), (3, f"a {short} b"), (4, f"c {short} d")])
    _, longest = repeats.repeated_windows(docs, 13, extend=True)
    assert {r.doc_id: r.longest for r in longest.collect()} == {1: 104, 2: 104, 3: 13, 4: 13}
    assert repeats.lengths(13) == [7, 13] and repeats.lengths(50) == [7, 13, 25, 50]


def test_sliding_min():
    x = np.array([5, 3, 8, 1, 9, 2, 7], np.uint64)
    for w in range(1, 8):
        assert repeats.sliding_min(x, w).tolist() == [min(x[i : i + w].tolist()) for i in range(len(x) - w + 1)]


# near duplicates


def classes(texts, size, percent):
    sets = {d: set(shingle_set(folded_words_of(t), size).tolist()) for d, t in texts.items()}
    parent = {d: d for d in texts}

    def root(d):
        while parent[d] != d:
            d = parent[d]
        return d

    for a, b in combinations(sorted(texts), 2):
        if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
            ra, rb = root(a), root(b)
            parent[max(ra, rb)] = min(ra, rb)
    return {d: (len(sets[d]), root(d)) for d in texts}


@pytest.mark.parametrize("size,percent", [(3, 85), (5, 80)])
def test_near_duplicates_by_brute_force(spark, documents, size, percent):
    """Chains, groups of copies and near copies, and texts just under the threshold."""
    rng = random.Random(percent)
    texts = {}
    for base in range(6):
        words = prose(rng, 150).split()
        for copy in range(14):
            w = words[:]
            for _ in range(rng.randrange(0, 9)):
                w[rng.randrange(len(w))] = rng.choice(WORDS)
            texts[len(texts)] = " ".join(w)
            if copy % 5 == 0:
                words = w
    texts |= {200 + i: texts[0].upper() for i in range(5)} | {300: None, 301: "", 302: "one two", 303: "One  two", 304: "one"}
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in neardup.group(documents(list(texts.items())), size, percent).collect()}
    assert got == classes(texts, size, percent)


def test_near_duplicate_defined_cases(spark, documents):
    rows = documents([(5, "a b c d"), (5, "a b c d"), (3, "a b c d"), (None, "a b c d"), (7, None)])
    got = sorted(((r.doc_id or 0, r.component_id, r.kept) for r in neardup.group(rows).collect()), key=str)
    assert got == sorted([(5, 3, False), (5, 3, False), (3, 3, True), (0, None, True), (7, 7, True)], key=str)
    assert neardup.group(documents([])).count() == 0
    assert [r.doc_id for r in neardup.keep_one(rows).orderBy("doc_id").collect()] == [None, 3, 7]


def test_banding_misses_less_than_one_in_a_million():
    for percent in (50, 80, 85, 95):
        bands, rows = neardup.banding(percent)
        assert bands * rows <= neardup.FUNCTIONS and (1 - (percent / 100) ** rows) ** bands <= neardup.MISS


def test_bitmap_bounds_the_difference():
    rng = np.random.default_rng(0)
    for n in (5, 100, 5000):
        a = rng.integers(0, 2**63, n).astype(np.uint64)
        b = np.concatenate((a[: n // 2], rng.integers(0, 2**63, n // 3).astype(np.uint64)))
        bits = sum(bin((x ^ y) & (2**64 - 1)).count("1") for x, y in zip(neardup.bitmap(a), neardup.bitmap(b), strict=True))
        assert bits <= len(np.setxor1d(a, b))


# language


def test_language_held_out_and_undetermined(spark, documents):
    rng = random.Random(3)
    made = {"en": "the and of that with ing tion".split(), "fr": "les de une étais être où avec".split(), "de": "der und nicht über schön sein".split()}
    rows = [(i, " ".join(rng.choice(made[lang]) for _ in range(30)), lang) for i in range(240) for lang in [list(made)[i % 3]]]
    rows += [(900, None, "en"), (901, "123 !!", "en"), (902, "the and of", None), (903, "", "fr")]
    got = {r.doc_id: r for r in language.identify(documents(rows)).collect()}
    held = [r for r in got.values() if r.held_out and r.doc_id < 900]
    assert held and all(r.lang_pred == r.lang for r in held)
    assert [got[i].lang_pred for i in (900, 901, 903)] == ["und"] * 3 and got[900].score == 0
    assert got[902].lang_pred == "en" and all(0 <= r.score <= 1 for r in got.values())
    import zlib

    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in got.values())


def test_language_without_anything_to_learn(spark, documents):
    assert {r.lang_pred for r in language.identify(documents([(1, "words", None)])).collect()} == {"und"}
    assert language.identify(documents([])).count() == 0


def slow_vector(text, size=language.DIMENSIONS):
    """A text's vector letter by letter: fold, collapse gaps, rotate, bind, bundle."""
    symbols = [0]
    for c in text:
        low = c.lower()[0] if c.isalpha() else None
        code = 0 if low is None else ord(low) - 96 if "a" <= c.lower() <= "z" else ord(low)
        if code or symbols[-1]:
            symbols.append(code)
    if symbols[-1]:
        symbols.append(0)
    vectors = [language._letters(np.array([x]), size)[0].astype(float) for x in symbols]
    total = np.zeros(size)
    for a, b, c in zip(vectors, vectors[1:], vectors[2:], strict=False):
        total += np.roll(a, 2) * np.roll(b, 1) * c
    return total / np.linalg.norm(total)


def test_language_vectors_by_a_slow_reference():
    texts = ["Où est l'été?", "plain words, twice  twice", "Привет, мир", "ΑΒΓ αβγ x", "1 2 é", "漢字かな 漢"]
    got, known = language.text_vectors([*texts, "", None, "12 !"], language.DIMENSIONS)
    assert known.tolist() == [True] * len(texts) + [False] * 3
    for text, v in zip(texts, got, strict=False):
        assert np.allclose(v, slow_vector(text), atol=1e-5), text


def test_languages_of_one_other_script_are_told_apart(spark, documents):
    rng = random.Random(4)
    made = {"a": "что это как его она они была".split(), "b": "що це як його вона вони була її".split(), "c": "και το της που με για".split()}
    rows = [(i, " ".join(rng.choice(made[lang]) for _ in range(25)), lang) for i in range(300) for lang in [list(made)[i % 3]]]
    held = [r for r in language.identify(documents(rows)).collect() if r.held_out]
    assert held and all(r.lang_pred == r.lang for r in held)


# personal data

PATTERNS = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def luhn(s):
    total = 0
    for i, c in enumerate(reversed(s)):
        v = int(c) * (1 + i % 2)
        total += v - 9 * (v > 9)
    return total % 10 == 0


def base_spans(text):
    out = []
    for kind, pattern in PATTERNS.items():
        for m in re.finditer(pattern, text):
            digits = re.sub("[^0-9]", "", m[0])
            good = {"email": True, "ip": kind != "ip" or all(int(x) <= 255 for x in m[0].split(".")), "card": 13 <= len(digits) <= 19 and luhn(digits), "phone": 9 <= len(digits) <= 15}[kind]
            if good:
                out.append(f"{kind}:{m.start()}:{m.end()}")
    return out


def test_base_spans_by_brute_force(spark, documents):
    rng = random.Random(4)
    bits = ["a.b@c.d", "@x.y", "a@b", "x@y.z_q@r.s.t", "1.2.3.4", "300.1.1.1", "0001.02.3.255.5.6.7", "4111 1111 1111 1111", "4111-1111-1111-1112", "+1 (555) 010-9999", "+1..2", "é😀", "12", "999999999999999999999999", "word", "+33 1 23 45 67 89", "a" * 300, "7" * 400]
    rows = [(i, " ".join(rng.choice(bits) + rng.choice(["", ".", ",", "\n"]) for _ in range(25))) for i in range(150)] + [(500, None), (501, ""), (502, "1 " * 4000), (503, "9" * 30000), (504, "a." * 20000)]
    got = {r.doc_id: r for r in private.digest(private.find(documents(rows))).collect()}
    for i, text in rows:
        want = base_spans(text or "")
        assert got[i].base_sha256 == hashlib.sha256(",".join(want).encode()).hexdigest(), i
        assert (got[i].n_email, got[i].n_ip, got[i].n_card, got[i].n_phone) == tuple(sum(w.startswith(k) for w in want) for k in PATTERNS)
        assert set(want) <= set(got[i].spans.split(",")) | {""}
    assert got[500].spans == ""


def test_model_adds_beside_the_base_and_redaction_covers_it(spark, documents):
    from pyspark.sql import functions as F

    docs = documents([(1, "write to a.b@c.de now, or +49 30 1234567"), (2, "plain words only")])
    picked = private.find(docs).join(docs.select("doc_id", "text"), "doc_id")
    out = {r.doc_id: r.t for r in picked.select("doc_id", private.redacted(F.col("text"), F.col("spans")).alias("t")).collect()}
    assert out == {1: "write to <email> now, or <phone>", 2: "plain words only"}


def card_number(rng, right):
    while True:
        digits = "4" + "".join(rng.choice("0123456789") for _ in range(15))
        if luhn(digits) == right:
            return digits


def test_planted_variants_are_added_and_lookalikes_are_not(spark, documents):
    rng = random.Random(11)
    rows, spots = [], {}
    for i in range(900):
        # Digits that pass the check digit are a card by the strict rule.
        n = next(n for n in iter(lambda: "".join(rng.choice("123456789") for _ in range(7)), None) if not luhn("004930" + n))
        c, d = card_number(rng, True), card_number(rng, False)
        kind, mark = [
            ("email", f"ann{n} (at) host{i % 9} (dot) com"),
            ("phone", f"0049 30 {n}"),
            ("phone", f"1 ({n[:3]}) 555-{n[3:]}"),
            ("card", ".".join(c[j : j + 4] for j in (0, 4, 8, 12))),
            ("strict", f"bob{n}@host.com or +49 30 {n} or {c}"),
            ("decoy", ".".join(d[j : j + 4] for j in (0, 4, 8, 12))),
            ("decoy", f"2024-01-{i % 20 + 10} 12{n[:4]}"),
            ("decoy", f"me (at) noon. Then{n}"),
            ("decoy", n + "12345"),
        ][i % 9]
        head = prose(rng, 6) + " see "
        rows.append((i, head + mark + ". " + prose(rng, 5)))
        spots[i] = (kind, f"{kind}:{len(head)}:{len(head) + len(mark)}")
    got = {r.doc_id: r.spans for r in private.digest(private.find(documents(rows))).collect()}
    for kind in ("email", "phone", "card"):
        own = [spots[i][1] in got[i].split(",") for i in got if spots[i][0] == kind]
        assert sum(own) >= 0.95 * len(own), kind
    added = [set(got[i].split(",")) - {"", *base_spans(text)} for i, text in rows if spots[i][0] == "decoy"]
    assert sum(map(bool, added)) <= 4


def test_trees_separate_a_table():
    rng = np.random.default_rng(1)
    rows = rng.integers(0, 4, (60, 5))
    good = ((rows[:, 1] > 1) & (rows[:, 3] < 2)).astype(float)
    model = private.boost(rows, good * 10, (1 - good) * 10)
    s = model.score(rows)
    assert s[good == 1].min() > s[good == 0].max()


def test_named_secrets_are_added_and_long_names_are_not(spark, documents):
    rng = random.Random(12)
    key = lambda: "".join(rng.choice("0123456789abcdef") for _ in range(32))
    rows, planted = [], {}
    for i in range(400):
        token, slug = key(), f"report-{rng.randrange(10**4)}-of-{rng.randrange(10**6)}-final"
        head = f"{prose(rng, 5)} "
        body = f'token = "{token}"' if i % 2 else f"see {slug} there"
        if i % 2:
            planted[i] = f"secret:{len(head) + 9}:{len(head) + 41}"
        rows.append((i, f"{head}{body} {prose(rng, 3)}"))
    got = {r.doc_id: (r.spans, r.n_secret) for r in private.digest(private.find(documents(rows))).collect()}
    assert {i: s for i, (s, n) in got.items() if n} == planted
    assert sum(n for _, n in got.values()) == len(planted)


# packing


def test_packing_keeps_every_word_and_both_conflicts(spark, documents):
    rng = random.Random(5)
    rows = [(i, prose(rng, rng.randrange(1, 120)), "en", "hot" if i % 3 == 0 else f"s{i % 7}") for i in range(300)]
    rows += [(1000 + i, rows[0][1], "en", "hot") for i in range(40)] + [(2000, prose(rng, 1000), "en", None), (2001, None), (2002, " ")]
    out = packing.pack(documents(rows), capacity=200, per_source=2, shard=100).collect()
    words = {}
    for r in out:
        words[r.doc_id] = words.get(r.doc_id, 0) + r.n_words
    assert words == {r[0]: len((r[1] or "").split()) for r in rows}
    bins = {}
    for r in out:
        if r.bin_id is not None:
            bins.setdefault(r.bin_id, []).append(r)
    for held in bins.values():
        assert sum(r.n_words for r in held) <= 200
        assert len({r.cluster for r in held}) == len(held)
        for s in {r.source for r in held}:
            assert sum(r.source == s for r in held) <= 2
        at = 0
        for r in sorted(held, key=lambda r: r.place):
            assert r.at == at
            at += r.n_words
    assert {r.doc_id for r in out if r.bin_id is None} == {2001, 2002}
    assert packing.pack(documents([])).count() == 0


def test_packing_keeps_large_ids_beside_nulls_and_repeats(spark, documents):
    ids = [9007199254740993, 9007199254740995, 2**63 - 1, None, None, 7, 7]
    out = packing.pack(documents([(i, f"text {n} of some words") for n, i in enumerate(ids)])).collect()
    assert sorted((r.doc_id is None, r.doc_id) for r in out if r.doc_id is not None) == sorted((False, i) for i in ids if i is not None)
    assert sum(r.doc_id is None for r in out) == 2 and {r.n_words for r in out} == {5}


def test_best_fit_takes_the_tightest_compatible_bin():
    rng = random.Random(6)
    pieces = sorted(((rng.randrange(1, 60), rng.randrange(4), rng.randrange(30)) for _ in range(200)), key=lambda p: -p[0])
    bins = []
    for (words, source, cluster), got in zip(pieces, packing.best_fit(pieces, 100, 2), strict=True):
        fits = [i for i, b in enumerate(bins) if b["room"] >= words and cluster not in b["clusters"] and b["sources"].count(source) < 2]
        want = min(fits, key=lambda i: (bins[i]["room"], i)) if fits else len(bins)
        assert got == want
        if want == len(bins):
            bins.append({"room": 100, "clusters": set(), "sources": []})
        bins[want]["room"] -= words
        bins[want]["clusters"].add(cluster)
        bins[want]["sources"].append(source)
