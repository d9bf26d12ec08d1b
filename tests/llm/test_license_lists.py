"""Notices that follow one another closely are all found."""

import random

import pytest

from pathlore.llm import license_scan

INDEX = license_scan.LicenseIndex.build(license_scan.TEMPLATES)


def spans(text):
    return [(x[0], x[3], x[4]) for x in INDEX.scan(text)]


def every_occurrence(text, names):
    """All places of the templates' words, by plain search."""
    out = []
    for name in names:
        notice, at = license_scan.TEMPLATES[name].rstrip("."), 0
        while (at := text.find(notice, at)) >= 0:
            out.append((name, at, at + len(notice)))
            at += len(notice)
    return sorted(out, key=lambda x: x[1])


def test_two_neighbouring_notices():
    text = "foo Released under the MIT License. bar Released under the MIT License."
    assert spans(text) == [("mit-notice", 4, 34), ("mit-notice", 40, 70)]


@pytest.mark.parametrize("gap", range(5))
def test_lists_of_notices_equal_brute_force(gap):
    rng = random.Random(gap)
    names = ["mit-notice", "gpl-3.0-notice", "cc-by-nc-4.0-notice", "mpl-2.0-notice"]
    for chosen in ([names[0]], [names[1]], [names[2]], names):
        lines = [" ".join([f"word{rng.randrange(99)}"] * rng.randint(0, gap) + [license_scan.TEMPLATES[rng.choice(chosen)]]) for _ in range(40)]
        text = "\n".join(lines)
        want = every_occurrence(text, chosen)
        assert len(want) == 40 and spans(text) == want


def test_ties_prefer_the_shorter_span():
    assert license_scan.align([1, 2, 3], [1, 9, 1, 2, 3], 0) == (3, 2, 4)


# ---- the index and the alignment against looking at everything -----------------------------------------------------------


def old_way(template, words, shift, band):
    """The best chain of matches in the band, cell by cell."""
    best = {}
    for i, t in enumerate(template):
        fresh = {}
        for j in range(max(0, i + shift - band), min(len(words), i + shift + band + 1)):
            if words[j] == t:
                m, f, _ = max(((m, f, -at) for at, (m, f) in best.items() if at < j), default=(0, j, 0))
                fresh[j] = (m + 1, f if m else j)
        for j, x in fresh.items():
            best[j] = max(x, best.get(j, x))
    return max(((m, f - j, -f, j) for j, (m, f) in best.items()), default=(0, 0, 0, 0))


def test_alignment_equals_cell_by_cell():
    rng = random.Random(4)
    for _ in range(800):
        k, band = rng.randint(1, 5), rng.randint(0, 6)
        a, b = ([rng.randint(1, k) for _ in range(rng.randint(0, 14))] for _ in range(2))
        shift = rng.randint(-6, 10)
        m, span, first, last = old_way(a, b, shift, band)
        got = license_scan.align(a, b, shift, band)
        assert got == ((m, -first, last) if m else (0, 0, 0)) and (not m or got[1] - got[2] == span)


def everything(index, text):
    """The spans when every template is aligned on every diagonal."""
    low = license_scan.lower_in_place(text)
    ids = [index.numbers.get(w, 0) for w in license_scan.WORD.findall(low)]
    found, taken = [], []

    def look(name, shift, lo, hi):
        t = index.words[name]
        m, a, b = license_scan.align(t, ids[lo:hi], shift - lo)
        if m >= license_scan.LEAST_COVERAGE * len(t):
            found.append((-m, -m / len(t), name, lo + a, lo + b, shift, lo, hi))

    for name, t in index.words.items():
        for shift in range(-len(t), len(ids) + 1):
            look(name, shift, max(0, shift - license_scan.BAND), min(len(ids), shift + len(t) + license_scan.BAND))
    kept = []
    while found:
        m, c, name, a, b, shift, lo, hi = x = min(found)
        found.remove(x)
        parts = [*license_scan.free_parts(lo, hi, sorted(taken))]
        if any(p <= a and b < q for p, q in parts):
            kept.append((name, -c, -m, a, b))
            taken.append((a, b))
            parts = [*license_scan.free_parts(lo, hi, sorted(taken))]
        for part in parts:
            look(name, shift, *part)
    places = [m.span() for m in license_scan.WORD.finditer(low)]
    return sorted(((n, c, m, places[a][0], places[b][1]) for n, c, m, a, b in kept), key=lambda x: x[3])


def test_index_finds_what_looking_everywhere_finds():
    names = ["mit-notice", "apache-2.0-notice", "cc-by-4.0-notice", "gpl-3.0-notice", "mpl-2.0-notice", "bsd-clause"]
    index = license_scan.LicenseIndex.build({n: license_scan.TEMPLATES[n] for n in names})
    rng = random.Random(8)
    spans = 0
    for _ in range(60):
        words = []
        for _ in range(rng.randint(1, 4)):
            words += [rng.choice(["the", "license", "under", "sea", "version"]) for _ in range(rng.randint(0, 5))] + ["sea"] * (2 * license_scan.BAND)
            notice = license_scan.TEMPLATES[rng.choice(names)].split()
            if len(notice) > 10 and rng.random() < 0.5:  # an edit that leaves four neighbouring words
                notice[rng.randrange(len(notice))] = "edited"
            words += notice
        text = " ".join(words)
        spans += len(index.scan(text))
        assert index.scan(text) == everything(index, text)
    assert spans > 100


def test_whole_texts_of_licenses():
    index = license_scan.LicenseIndex.build(license_scan.TEMPLATES)
    for name in ("mit", "isc", "bsd-2-clause", "bsd-3-clause", "zlib", "unlicense"):
        words = license_scan.TEMPLATES[name].split()
        edited = " ".join(w for i, w in enumerate(words) if i % 13 != 7)
        best = max(index.scan("Copyright by nobody. " + edited + " The end."), key=lambda x: x[2])
        assert best[0] == name and 0.9 < best[1] < 1


def test_templates_short_empty_and_none(spark, tmp_path):
    import pytest

    short = license_scan.LicenseIndex.build({"one": "Copyleft", "two": "All rights"})
    assert [(x[0], x[3], x[4]) for x in short.scan("copyleft, all rights reserved")] == [("one", 0, 8), ("two", 10, 20)]
    with pytest.raises(ValueError):
        license_scan.LicenseIndex.build({"none": " ... "})
    docs = spark.createDataFrame([(1, license_scan.TEMPLATES["mit-notice"], "k")], "doc_id long, text string, license string")
    assert license_scan.scan_licenses(docs, {}).count() == 0 and license_scan.scan_licenses(docs).count() == 1
    (tmp_path / "own.txt").write_text("Do what you like with this text of mine.")
    own = license_scan.read_templates({"own": str(tmp_path / "own.txt")})
    assert license_scan.scan_licenses(docs.selectExpr("doc_id", "'so do what you like with this text of mine' AS text"), own).first().license == "own"
