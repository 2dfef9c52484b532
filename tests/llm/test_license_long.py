"""License scans of long lines, many notices, other templates, and against brute force."""

import random

from fedlake.llm import license_scan as L


def words(n, seed):
    r = random.Random(seed)
    return " ".join("".join(r.choice("abcdefghijklmnop") for _ in range(r.randint(2, 9))) for _ in range(n))


def names(text):
    scanner = L.Scanner()
    return {(name, w.verdict) for _, block in L.blocks(text) for name, _, w in scanner.match(block)}


def test_every_template_is_found_at_any_place_of_a_long_line():
    for seed, (name, template) in enumerate(L.TEMPLATES):
        for before, after in ((0, 2000), (2000, 0), (137 * (seed + 1), 900), (20_000, 3)):
            assert (name, "exact") in names(f"{words(before, seed)} {template} {words(after, seed + 99)}"), (name, before, after)


def test_notices_of_one_line_are_all_found():
    chosen = [L.TEMPLATES[k] for k in (1, 5, 9, 10)]
    text = f" {words(300, 5)} ".join(t for _, t in chosen)
    assert {n for n, _ in chosen} <= {n for n, v in names(text) if v == "exact"}
    assert names(words(3000, 3) + " license " + words(3000, 4)) == set()


def test_windows_hold_every_stretch():
    block = words(700, 1) + "x" * 3000 + words(400, 2)
    for size in (256, 512):
        cut = L.windows(block, size)
        assert cut[0][0] == 0 and all(block[a : a + len(w)] == w and len(w) <= 4 * size for a, w in cut)
        for at in range(0, len(block) - size, 7):
            assert any(a <= at and at + size <= a + len(w) for a, w in cut)


def test_other_templates(spark):
    mine = (("LicenseRef-house", "You get these files as they stand and nobody answers for them at all."),)
    docs = spark.createDataFrame([(1, words(500, 7) + " " + mine[0][1]), (2, words(500, 8)), (3, None)], "doc_id long, text string")
    got = {r.doc_id: (r.licenses, r.verdict) for r in L.scan_documents(docs, mine).collect()}
    assert got == {1: ("LicenseRef-house", "exact"), 2: ("", "none"), 3: ("", "none")}


def test_documents_equal_brute_force(spark, folder):
    """Every exact notice that a plain search of normalised words finds is reported, and no other exact one."""
    rows = spark.read.parquet(f"{folder}/documents.parquet").select("doc_id", "text").collect()
    flat = lambda t: " " + " ".join(L._WORD.findall((t or "").lower())) + " "
    wanted = {r.doc_id: {n for n, t in L.TEMPLATES if flat(t) in flat(r.text)} for r in rows}
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got: dict[int, set] = {r.doc_id: set() for r in rows}
    for r in L.scan_blocks(docs).where("verdict = 'exact'").collect():
        got[r.doc_id].add(r.license)
    for k, found in wanted.items():
        assert got[k] <= found
        longest = {n for n in found if not any(n != m and any(flat(t) in flat(u) for _, t in L.TEMPLATES if _ == n for v, u in L.TEMPLATES if v == m) for m in found)}
        assert longest <= got[k]
