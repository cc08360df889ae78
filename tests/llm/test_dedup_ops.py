import random
import subprocess
import sys
from pathlib import Path

import brute
import numpy as np
import pytest

from pairlens.llm import minhash_dedup, substring_dedup, suffix_dedup

pytestmark = pytest.mark.usefixtures("spark")
DOCS = "doc_id long, text string, lang string"


def near_copies(n, seed, edits):
    """Copies of one text with words replaced, at similarities around the threshold."""
    r = random.Random(seed)
    base = [f"w{r.randint(0, 10**6)}" for _ in range(120)]
    out = []
    for i in range(n):
        w = list(base)
        for _ in range(r.randint(0, edits)):
            w[r.randrange(len(w))] = f"x{r.randint(0, 10**6)}"
        out.append((i, " ".join(w), "en"))
    r.shuffle(out)
    return out


@pytest.mark.parametrize("edits", [4, 7])
def test_near_duplicates_equal_all_pairs(spark, edits):
    docs = near_copies(150, edits, edits)
    docs += [(1000, None, "en"), (1001, "", "en"), (1002, " \t", "en"), (1003, "one two", "en"), (1004, "One TWO", None), (1005, "one", "en"), (1006, docs[0][1], "en")]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in minhash_dedup.near_duplicates(spark.createDataFrame(docs, DOCS), shingle=4).collect()}
    assert got == brute.components([d[:2] for d in docs])


def test_near_duplicates_of_the_given_documents(spark):
    df = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in minhash_dedup.near_duplicates(df, shingle=4).collect()}
    assert got == brute.components([(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()])


@pytest.mark.parametrize("blocks", [None, (40, 100, 4_000, 9_000)])
def test_a_large_group_of_near_copies(spark, monkeypatch, blocks):
    """One bucket holds hundreds that are near the threshold: the result is whole and no stage makes rows by pairs."""
    if blocks:
        for name, x in zip(("QUERY_ROWS", "MEMBER_ROWS", "QUERY_SHINGLES", "MEMBER_SHINGLES"), blocks, strict=True):
            monkeypatch.setattr(minhash_dedup, name, x)
    docs, rows = near_copies(900, 31, 9), {}
    monkeypatch.setattr(minhash_dedup, "LEADERS", 1)
    scratch, keep = minhash_dedup.Scratch(spark, "near"), minhash_dedup.Scratch.keep

    def counted(self, df, tag):
        out = keep(self, df, tag)
        rows[tag] = out.count()
        return out

    monkeypatch.setattr(minhash_dedup.Scratch, "keep", counted)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in minhash_dedup.near_duplicates(spark.createDataFrame(docs, DOCS), shingle=4, scratch=scratch).collect()}
    assert got == brute.components([d[:2] for d in docs])
    assert rows["maybe"] > 0 and rows["rest-links"] > 0 and max(rows.values()) <= 33 * len(docs) and rows["rest-links"] <= 2 * len(docs)


def test_near_duplicates_of_nothing(spark):
    assert minhash_dedup.near_duplicates(spark.createDataFrame([], DOCS)).collect() == []
    rows = minhash_dedup.near_duplicates(spark.createDataFrame([(None, "a b c", "x"), (1, "a b c", "x"), (1, "a b c", "x")], DOCS)).collect()
    assert len(rows) == 3 and {(r.component_id, r.kept) for r in rows} == {(1, True), (1, False)}  # a null key belongs to its class but isn't its least


def test_tree_nodes_equal_brute_force():
    rng = np.random.default_rng(4)
    for trial in range(80):
        v = rng.integers(0, 20 if trial % 2 else 10**9, rng.integers(1, 60)).astype(np.uint64)
        t = int(rng.integers(1, 10))
        exp = set()
        for i in np.flatnonzero(v).tolist():
            a = b = i
            while a > 0 and v[a - 1] > v[i]:
                a -= 1
            while b < len(v) - 1 and v[b + 1] >= v[i]:
                b += 1
            if b - a + 1 >= t:
                exp.add((a, i, b))
        assert set(zip(*(x.tolist() for x in substring_dedup.nodes(v, t)), strict=True)) == exp


def test_passages_are_found_and_cut(spark):
    r = random.Random(2)
    vocab = ["".join(r.choice("abcdefghij") for _ in range(5)) for _ in range(4000)]
    words = lambda n: [r.choice(vocab) for _ in range(n)]
    p, line = words(60), words(12)
    near, more = [*p[:20], "changed", *p[21:]], [*p[:30], "new", *p[30:]]
    plant = lambda x: " ".join([*words(40), *x, *words(40)])
    docs = [(i, " ".join(words(200)), "en") for i in range(20)] + [(100, plant(p), "en"), (101, plant(p), "en"), (102, plant(near), "en"), (103, plant(more), "en"), (104, " ".join(p), "en"), (105, None, "en"), (106, "", None)]
    docs += [(200 + i, plant(line), "en") for i in range(20)]
    df = spark.createDataFrame(docs, DOCS)
    found = substring_dedup.repeated_passages(df)
    rows = found.collect()
    assert {x.doc_id for x in rows} == {101, 102, 103, 104} and {(x.doc_id, x.first_doc_id) for x in rows} >= {(k, 100) for k in (101, 102, 103, 104)}
    assert {(x.start, x.end) for x in rows if x.doc_id == 101} == {(40, 100)}
    left = {x.doc_id: x for x in substring_dedup.drop_passages(df, found).collect()}
    assert len(left[101].text.split()) == 80 and left[104].text == "" and left[105].text is None and left[7].text == docs[7][1] and left[106].lang is None


def test_passages_whose_least_document_differs(spark):
    """Two later documents share a passage that the least document of their signatures doesn't have."""
    r = random.Random(9)
    words = lambda n: [f"v{r.randint(0, 10**7)}" for _ in range(n)]
    phrase, tail = words(8), words(60)
    docs = [(1, " ".join(words(60) + phrase + words(60)), "")] + [(i, " ".join(words(60) + phrase + tail + words(30)), "") for i in (2, 3, 4)]
    got = {(x.doc_id, x.first_doc_id) for x in substring_dedup.repeated_passages(spark.createDataFrame(docs, DOCS)).collect()}
    assert {3, 4} <= {a for a, _ in got} and 1 not in {b for _, b in got}


def span_check(docs, rows):
    import hashlib

    exp, texts = brute.removed([d[:2] for d in docs]), {d[0]: (d[1] or "").encode() for d in docs}
    for x in rows:
        gone, b = exp[x.doc_id], texts[x.doc_id]
        kept = bytes(c for i, c in enumerate(b) if i not in gone)
        assert (x.n_bytes, x.n_removed, x.n_spans, x.kept_sha256) == (len(b), len(gone), sum(i - 1 not in gone for i in gone), hashlib.sha256(kept).hexdigest()), x.doc_id


def test_suffix_dedup_equals_brute_force(spark):
    r = random.Random(5)
    parts = ["".join(r.choice("ab \0é") for _ in range(70)) for _ in range(6)]
    docs = [(i, "".join(r.choice(parts)[r.randint(0, 15) : r.randint(40, 70)] for _ in range(r.randint(0, 6))), "") for i in range(150)]
    docs += [(1000, None, None), (1001, "", ""), (1002, "a" * 500, ""), (1003, "a" * 300, ""), (1004, "b" * 49, ""), (1005, "a" * 500, "")]
    rows = suffix_dedup.remove_repeats(spark.createDataFrame(docs, DOCS)).collect()
    assert len(rows) == len(docs)
    span_check(docs, rows)
    assert suffix_dedup.remove_repeats(spark.createDataFrame([], DOCS)).collect() == []


def test_a_gram_in_pieces_is_merged():
    r = random.Random(3)
    for step in (1, 3, 7, 1000):
        parts = ["".join(r.choice("ab\0") for _ in range(90)) for _ in range(3)]
        docs = [(i, "".join(r.choice(parts)[r.randint(0, 15) : r.randint(60, 90)] for _ in range(r.randint(0, 4)))) for i in range(40)]
        rows = []
        for d, t in docs:
            if len(t) >= 50:
                _, _, _, at, n, least = suffix_dedup.runs([t.encode()], 50, 24)
                rows += [(g, d, 0, p, t.encode()[p : p + c + 49]) for p, c, g in zip(at.tolist(), n.tolist(), least.view(np.int64).tolist(), strict=True)]
        rows.sort(key=lambda x: x[:2])
        shard, got = suffix_dedup.Shard(50), {d: set() for d, _ in docs}
        for i in range(0, len(rows), step):
            for d, _, spans in shard.solve(rows[i : i + step]):
                for a, b in zip(spans[::2], spans[1::2], strict=True):
                    got[d] |= set(range(a, b))
        assert got == brute.removed(docs)


def test_suffix_array_and_prefixes():
    r = random.Random(1)
    for _ in range(60):
        b = bytes(r.choice(b"ab\0") for _ in range(r.randint(1, 80)))
        t = np.frombuffer(b, np.uint8)
        sa, word = suffix_dedup.suffix_array(t)
        exp = sorted(range(len(b)), key=lambda i: b[i:])
        assert sa.tolist() == exp
        lcp = suffix_dedup.common_prefixes(t, sa, word).tolist()
        common = lambda x, y: next((i for i, (p, q) in enumerate(zip(x, y, strict=False)) if p != q), min(len(x), len(y)))
        assert lcp == [0, *(common(b[i:], b[j:]) for i, j in zip(exp, exp[1:], strict=False))]


def passages_of(spark, docs):
    return {(x.doc_id, x.first_doc_id) for x in substring_dedup.repeated_passages(spark.createDataFrame(docs, DOCS)).collect()}


def test_near_passages_that_the_least_document_lacks(spark):
    """Documents 2 and 3 of each trio differ in one word, document 1 in two more: only 2 and 3 are near."""
    r = random.Random(21)
    words = lambda n: [f"q{r.randint(0, 10**8)}" for _ in range(n)]
    docs = []
    for i in range(60):
        p = words(50)
        one, three = [*p[:8], "x", *p[9:40], "y", *p[41:]], [*p[:25], "z", *p[26:]]
        docs += [(3 * i + j, " ".join([*words(60), *x, *words(60)]), "") for j, x in enumerate((one, p, three))]
    got = passages_of(spark, docs)
    missed = [i for i in range(60) if (3 * i + 2, 3 * i + 1) not in got]
    assert len(missed) <= 1 and not {b for _, b in got} & {3 * i for i in range(60)}


def test_passages_that_the_least_document_cuts_off(spark):
    """Document 1 of each trio ends with the first 44 words of a passage that 2 and 3 begin with."""
    r = random.Random(22)
    words = lambda n: [f"q{r.randint(0, 10**8)}" for _ in range(n)]
    docs = []
    for i in range(60):
        p = words(50)
        docs += [(3 * i, " ".join([*words(60), *p[:44]]), ""), (3 * i + 1, " ".join([*p, *words(60)]), ""), (3 * i + 2, " ".join([*p, *words(60)]), "")]
    got = passages_of(spark, docs)
    assert [i for i in range(60) if (3 * i + 2, 3 * i + 1) not in got] == []


def test_passages_that_go_on_past_the_least_document(spark):
    """Document 1 of each trio has the first 90 of the 100 words that 2 and 3 share: the last ten are found, too."""
    r = random.Random(23)
    words = lambda n: [f"q{r.randint(0, 10**8)}" for _ in range(n)]
    docs = []
    for i in range(40):
        p = words(100)
        docs += [(3 * i, " ".join([*words(60), *p[:90]]), ""), (3 * i + 1, " ".join([*p, *words(60)]), ""), (3 * i + 2, " ".join([*p, *words(60)]), "")]
    ends: dict = {}
    for x in substring_dedup.repeated_passages(spark.createDataFrame(docs, DOCS)).collect():
        ends[x.doc_id] = max(x.end, ends.get(x.doc_id, 0))
    assert [i for i in range(40) if ends.get(3 * i + 1) != 90 or ends.get(3 * i + 2) != 100] == []


def test_exact_copies_of_a_second_place(spark):
    """Document 1 of each pair has an edited version of a passage, then the passage itself, which document 2 copies."""
    r = random.Random(24)
    words = lambda n: [f"q{r.randint(0, 10**8)}" for _ in range(n)]
    docs = []
    for i in range(60):
        p = words(50)
        edited = [*p[:8], "x", *p[9:40], "y", *p[41:]]
        docs += [(2 * i, " ".join([*words(30), *edited, *words(2), *p, *words(30)]), ""), (2 * i + 1, " ".join([*words(60), *p, *words(60)]), "")]
    got = passages_of(spark, docs)
    assert [i for i in range(60) if (2 * i + 1, 2 * i) not in got] == []


def edited(r, p, edits):
    p = list(p)
    for _ in range(edits):
        p[r.randrange(len(p))] = f"x{r.randint(0, 10**8)}"
    return p


@pytest.mark.parametrize("cells", [None, (5, 9)])
def test_passages_equal_all_pairs(spark, monkeypatch, cells):
    """Every document that has a near passage in an earlier one is linked, at real and at tiny cells."""
    if cells:
        monkeypatch.setattr(substring_dedup, "QUERIES", cells[0])
        monkeypatch.setattr(substring_dedup, "MEMBERS", cells[1])
    r = random.Random(25)
    words = lambda n: [f"q{r.randint(0, 10**8)}" for _ in range(n)]
    docs = []
    for g in range(16):
        p = words(68)
        for i in range(15):
            docs.append((100 * g + i, " ".join([*words(r.randint(0, 40)), *edited(r, p, r.randint(0, 4)), *words(r.randint(0, 40))]), ""))
    exp = brute.near_pairs([d[:2] for d in docs])
    got = passages_of(spark, docs)
    asked, found = {a for a, _ in exp}, {a for a, _ in got}
    assert len(docs) >= 200 and len(asked) > 100
    assert len(asked & found) >= 0.98 * len(asked) and len(got - exp) <= 0.05 * len(got)


def test_near_passages_behind_decoys(spark):
    """Two later documents have a passage with one word changed; eight earlier ones hold twelve words of it each."""
    r = random.Random(26)
    words = lambda n: [f"q{r.randint(0, 10**8)}" for _ in range(n)]
    docs = []
    for i in range(100):
        p = words(68)
        docs += [(1000 * i + j, " ".join([*words(30), *p[8 * j : 8 * j + 12], *words(30)]), "") for j in range(8)]
        docs += [(1000 * i + 8, " ".join([*words(30), *p, *words(30)]), ""), (1000 * i + 9, " ".join([*words(30), *p[:34], "other", *p[35:], *words(30)]), "")]
    got = passages_of(spark, docs)
    assert sum((1000 * i + 9, 1000 * i + 8) in got for i in range(100)) >= 98


def test_passages_of_nothing(spark):
    df = spark.createDataFrame([], DOCS)
    found = substring_dedup.repeated_passages(df)
    assert found.collect() == [] and substring_dedup.drop_passages(df, found).collect() == []


def test_modules_import_what_their_workers_call():
    """Nobody else may have imported pyarrow.compute in a fresh worker: there the lists of op1's cells are still read."""
    code = "import pyarrow as pa\nfrom pairlens.llm import substring_dedup\nprint(substring_dedup._flat(pa.array([[{'x': 1}, {'x': 2}], [], [{'x': 3}]]))[0].tolist())\n"
    code += "import sys\nfrom pairlens.llm import minhash_dedup, suffix_dedup, token_counts\nprint(all(m.pc is sys.modules['pyarrow.compute'] for m in (minhash_dedup, suffix_dedup, token_counts)))"
    out = subprocess.run([sys.executable, "-c", code], cwd=Path(__file__).resolve().parents[2], capture_output=True, text=True, timeout=120)
    assert out.stdout.split("\n")[:2] == ["[0, 0, 2]", "True"], out.stderr
