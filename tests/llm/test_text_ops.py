import gzip
import random
import zlib

import brute
import pytest

from pairlens.llm import decontaminate, html_extract, packing, quality_rules, token_counts, url_filter, warc
from pairlens.llm.queries import RULES, tokenizer

DOCS = "doc_id long, text string, extra string"
TEXTS = [None, "", " a", "a \nb  c d", "x <|endoftext|> y<|endoftext|>z a", "é  b c  d 'e 's it's", "   ", "a\t b", "<s> not </s>", "long " * 3000, "word" * 3000, "ß　 x  y", "\x1c a \x1f b"]


def texts(spark):
    return spark.createDataFrame([(i, t, "x") for i, t in enumerate(TEXTS)] + [(1, "again", "x")], DOCS)


def test_token_counts_equal_the_library(spark):
    import sentencepiece

    m = sentencepiece.SentencePieceProcessor(model_file=tokenizer("piece_bpe_32k.model"))
    got = sorted((r.doc_id, r.n_bytes, r.n_tokens, r.over_limit) for r in token_counts.count_tokens(texts(spark), tokenizer("piece_bpe_32k.model")).collect())
    exp = sorted((i, len((t or "").encode()), n := len(m.encode(t or "")), n > 4096) for i, t in [*enumerate(TEXTS), (1, "again")])
    assert got == exp


def test_packing_is_whole_and_tight(spark):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer("byte_bpe_50k.json"))
    rows = packing.pack(texts(spark).where("not (doc_id = 1 and text = 'again')"), tokenizer("byte_bpe_50k.json")).collect()
    by: dict = {}
    for r in rows:
        by.setdefault(r.doc_id, []).append(r)
    for i, text in enumerate(TEXTS):
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 0]
        pieces = sorted(by[i], key=lambda r: r.piece)
        assert [p.start for p in pieces] == [sum(q.length for q in pieces[:k]) for k in range(len(pieces))] and sum(p.length for p in pieces) == len(ids)
        assert all(p.length == 2048 for p in pieces[1:])
        for p in pieces:
            assert p.ids_crc32 == zlib.crc32(b"".join(x.to_bytes(4, "little") for x in ids[p.start : p.start + p.length]))
    seqs: dict = {}
    for r in rows:
        seqs.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for s in seqs.values():
        at = 0
        for off, n in sorted(s):
            assert off == at
            at += n
        assert at <= 2048


def odd_texts(n, seed):
    r = random.Random(seed)
    parts = ["word", "a", "é", "ß", "日本", "1", "23", ".", "'s", "'", "<|endoftext|>", "<s>", "</s>", "<unk>", "▁", "😀", "\u200d", "\ufeff", "\x00", "\x7f", "\x85", "\xa0", "\u1680", "\u2003", "\u2028", "\u202f", "\u3000", "\x1c", "\x1f", "\x0b", "\x0c", "\r", "\t", "\n", "\n", " ", " ", " ", "  ", "-", "#", "!"]
    return ["".join(r.choice(parts) for _ in range(r.randint(0, 14))) for _ in range(n)]


@pytest.mark.parametrize("file", ["byte_bpe_50k.json", "piece_bpe_32k.model"])
def test_ids_of_odd_texts_equal_the_library(file):
    """White space of all kinds, control characters, special strings, line feeds: ids as the library gives them."""
    own = ["word\n\u3000", "a\n\x85b c", *odd_texts(6000, 77)]
    if file.endswith(".json"):
        from tokenizers import Tokenizer

        t = Tokenizer.from_file(tokenizer(file))
        exp = [x.ids for x in t.encode_batch(own, add_special_tokens=False)]
    else:
        import sentencepiece

        exp = sentencepiece.SentencePieceProcessor(model_file=tokenizer(file)).encode(own)
    ids, bounds = token_counts.memo(tokenizer(file))([x.encode() for x in own])
    assert [ids[a:b].tolist() for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)] == exp


def test_open_bins_take_the_fullest_and_close_it():
    b = packing.OpenBins(10, 2)
    assert [b.put(n) for n in (6, 7, 3, 4)] == [(0, 0), (1, 0), (1, 7), (0, 6)]
    b = packing.OpenBins(10, 2)
    assert [b.put(n) for n in (6, 8, 7, 4, 2)] == [(0, 0), (1, 0), (2, 0), (0, 6), (2, 7)]  # bin 1, the fullest, closed for bin 2


def test_url_rules(spark):
    urls = ["http://a.Example.COM/en/71?x", "https://example.com/en/8", "http://x.net/de/8", "http://m.example.net/de/81#a", "http://b.org/es", "http://b.org/es/", "http://notexample.com/en/7", None, "no scheme", "ftp://", "http://com/en/", "http://u@x.net:80/de/1\nq"]
    df = spark.createDataFrame([(i, u, 1) for i, u in enumerate(urls)] + [(0, urls[0], 2)], "page_id long, url string, host int")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_filter.judge(df, RULES).collect()}
    assert got[0] == ("a.example.com", "/en/71", "example.com/en/7", "allow") and got[1][2:] == ("com/en/", "block") and got[2][2:] == ("net/de/", "allow")
    assert got[3][2:] == ("example.net/de/8", "block") and got[4][2:] == (None, "allow") and got[5][2:] == ("org/es/", "block") and got[6][2:] == ("com/en/", "block")
    assert got[7] == got[8] == ("", "", None, "allow") and got[10] == ("com", "/en/", "com/en/", "block") and got[11][:2] == ("u@x.net:80", "/de/1\nq")
    assert url_filter.judge(df, RULES).count() == len(urls) + 1 and url_filter.judge(df, []).where("verdict = 'block'").count() == 0


def test_warc_round_trip(spark, tmp_path):
    big = "é" * 5000
    pages = [(1, "http://a/\r\nX: y", big), (2, None, big), (3, "u", "short"), (4, "u", "short"), (5, "u", None), (6, "u", "x" * 100), (7, "u", "x" * 100), (7, "u", "x" * 100)]
    df = spark.createDataFrame(pages, "page_id long, url string, html string")
    path = f"file://{tmp_path}/w"
    warc.write_pages(df, path)
    got = sorted((r.page_id, r.payload_bytes, r.record_type, r.refers_to) for r in warc.read_pages(spark, path).collect())
    assert got == [(1, 10000, "response", None), (2, 10000, "revisit", 1), (3, 5, "response", None), (4, 5, "response", None), (5, 0, "response", None), (6, 100, "response", None), (7, 100, "revisit", 6), (7, 100, "revisit", 6)]
    raw = spark.read.format(warc.FORMAT).load(path)
    assert {bytes(r.payload).decode() for r in raw.where("record_type = 'response'").collect()} == {big, "short", "", "x" * 100}
    bare = spark.read.format(warc.FORMAT).option("payload", "false").load(path).where("record_type = 'revisit'")
    assert bare.count() == 3 and all(r.payload is None for r in bare.collect())
    # other writers' files: members without the length field, and plain records
    for f in (tmp_path / "w").glob("*.warc.gz"):
        plain = gzip.decompress(f.read_bytes())
        (tmp_path / "p").mkdir(exist_ok=True)
        (tmp_path / "p" / f"{f.name}.warc").write_bytes(plain)
        (tmp_path / "g").mkdir(exist_ok=True)
        parts = plain.split(b"WARC/1.1")[1:]
        (tmp_path / "g" / f.name).write_bytes(b"".join(gzip.compress(b"WARC/1.1" + x) for x in parts))
    for other in ("p", "g"):
        assert sorted((r.page_id, r.payload_bytes, r.record_type, r.refers_to) for r in warc.read_pages(spark, f"file://{tmp_path}/{other}").collect()) == got
    (tmp_path / "none").mkdir()
    assert warc.read_pages(spark, f"file://{tmp_path}/none").count() == 0


PAGE = """<html><head><title>t</title><style>p{}</style><script>var a="</p>";</script></head><body><header>Top</header><nav><ul><li><a href=x>Home</a></ul></nav>
<div class="cookie-notice">We use cookies</div><div id=wrap><div class="main-content"><h1>Title &amp; more</h1><p>First  paragraph, with <b>bold</b> text,\n and <a href=y>a link</a> inside it.<p>Second&nbsp;one, also long enough to count, surely.
<!-- no --><ul><li>A point, made here<li>Another point</ul><form><input value=q><button>Go</button></form></div><aside>Side</aside><div class="comments"><p>I, a reader, say, hello, there, all of you</p></div></div><footer>Foot</footer></body></html>"""


def test_html_extraction(spark):
    exp = "Title & more\nFirst paragraph, with bold text, and a link inside it.\nSecond one, also long enough to count, surely.\nA point, made here\nAnother point"
    assert html_extract.main_text(PAGE) == exp
    assert html_extract.main_text(None) == html_extract.main_text("") == html_extract.main_text("<div>") == ""
    assert html_extract.main_text("just text &lt;b&gt;") == "just text <b>"
    assert html_extract.main_text("<p>open <b>bold<br><p>next</p>") == "open bold\nnext"
    rows = html_extract.extract(spark.createDataFrame([(1, "u", PAGE, 5), (2, None, None, 5)], "page_id long, url string, html string, text int")).collect()
    assert [(r.page_id, r.n_chars) for r in sorted(rows)] == [(1, len(exp)), (2, 0)]


def test_extraction_of_the_given_pages(spark):
    for r in spark.read.parquet("/root/testdata/sf0.001/pages.parquet").collect():
        text = html_extract.main_text(r.html)
        article = r.html.split("<article>")[1].split("</article>")[0]
        assert len(text) > 0.85 * len(article.replace("<p>", "").replace("</p>", "").replace("&amp;", "&")) - 40
        assert "©" not in text and "track(" not in text


def test_decontamination(spark):
    item = "A train with Zoe goes 90 miles in 4 hours and then Zoe walks 9 miles, so how far did she go in total today?"
    docs = [(1, "Intro. A train with Alice goes 60 km in 2 hours and then Alice walks 3 km, so how far did she go in total today? more", ""), (2, item.lower(), ""), (3, "A train with Bob goes 80 km in 5 hours and then Carl walks 80 km, so how far did she go in total today?", "")]
    docs += [(4, None, ""), (5, "", ""), (6, "A train goes somewhere and nothing else matters here at all today", ""), (7, "word " * 30000 + item, ""), (2, item.lower(), "")]
    b = spark.createDataFrame([(9, item), (10, None), (11, "tiny"), (9, item)], "item_id long, text string")
    d = spark.createDataFrame(docs, DOCS)
    got = {(r.doc_id, r.item_id) for r in decontaminate.contaminated(d, b).collect()}
    assert got == {(1, 9), (2, 9), (7, 9)}
    assert decontaminate.contaminated(d, b.where("item_id = 11")).count() == 0
    assert decontaminate.contaminated(d.where("doc_id < 0"), b).count() == 0


NAMES = "Anna Omar Maria Chen Zoe Ravi Lena Tariq Ines Bruno Keiko Pavel".split()
PLACES = "Lisbon Cairo Osaka Quito Bergen Hanoi Tunis Perth".split()
FORMS = [
    "{a} has {x} red apples. {a} gives {y} of them away. {a} buys {z} more at noon. {a} sells {y}. How many apples remain?",
    "A train leaves {p} at {x} and reaches {q} after {y} hours, so how far did {a} and {b} go if it runs {z} km an hour?",
    "{a} and {b} share {x} euros in the ratio {y} to {z}. How many euros does {b} get, and how many more would {a} need?",
    "On Monday {a} drives from {p} to {q}, a distance of {x} km, in {y} hours and rests {z} minutes; what was the mean speed?",
    "If {a} reads {x} pages a day and {b} reads {y} pages a day, after how many days have both of them read {z} pages?",
]


def test_items_are_found_with_other_values_and_letter_cases(spark):
    """Recall on items with other names and numbers and in other letter cases; other questions stay clean."""
    r = random.Random(31)
    fill = lambda f: f.format(**dict(zip("ab", r.sample(NAMES, 2), strict=True)), **dict(zip("pq", r.sample(PLACES, 2), strict=True)), **dict(zip("xyz", r.sample(range(2, 99), 3), strict=True)))
    items = [(i, fill(f)) for i, f in enumerate(FORMS)]
    words = lambda n: " ".join(r.choice("and the of ran by lake tree house was on under night word page run".split()) for _ in range(n))
    own = [(i, how(fill(f) if how is str else items[i][1])) for i, f in enumerate(FORMS) for how in (str,) * 20 + (str.lower, str.upper, str.title)]
    docs = [(k, f"{words(30)}. {t} {words(30)}", i) for k, (i, t) in enumerate(own)]
    clean = [(1000 + k, f"{words(20)}. {r.choice(NAMES)} walks {r.randint(2, 99)} km to {r.choice(PLACES)}. {words(30)}", -1) for k in range(60)]
    d = spark.createDataFrame(docs + clean, "doc_id long, text string, extra long")
    got = {(x.doc_id, x.item_id) for x in decontaminate.contaminated(d, spark.createDataFrame(items, "item_id long, text string")).collect()}
    exp = {(k, i) for k, _, i in docs}
    assert len(got & exp) >= 0.95 * len(exp) and not got - exp
    assert not [k for k, (i, t) in enumerate(own) if t.lower() == items[i][1].lower() and (k, i) not in got]


def test_decontamination_finds_the_planted_items(spark):
    docs, b = (spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet") for t in ("documents", "benchmark"))
    exp = {(x.doc_id, y.item_id) for x in docs.collect() for y in b.collect() if y.text in x.text}
    assert {(r.doc_id, r.item_id) for r in decontaminate.contaminated(docs, b).collect()} == exp


def test_statistics_equal_brute_force(spark):
    r = random.Random(1)
    own = [" ".join(r.choice("abc") for _ in range(r.randint(0, 40))) + r.choice(["", "\n", "\n\nx y\nx y"]) for _ in range(60)] + ["#* $|<\x0b>", "a b c d e a b c d e", "  x", "x " * 20000]
    docs = [(i, t, "x") for i, t in enumerate([*TEXTS, *own])]
    rows = quality_rules.judge(spark.createDataFrame(docs, DOCS), quality_rules.DecisionList()).collect()
    for x in rows:
        exp = brute.stats(docs[x.doc_id][1])
        assert (x.n_words, x.word_chars, x.n_symbols, x.n_dup_lines, x.n_repeat_words) == exp, x.doc_id
        assert x.base_failed == (exp[0] < 10 or 100 * exp[4] > 20 * exp[0]) and x.kept == (not x.base_failed)


@pytest.mark.parametrize("split", ["doc_id % 2 = 0", "doc_id % 2 = 1", "doc_id % 3 < 2", "doc_id % 3 > 0"])
def test_rules_are_learned_and_hold_out(spark, split):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    rules = quality_rules.learn(docs, labels.where(split))
    assert 1 <= len(rules.rules) <= 12
    assert all(c.cut != 0 for r in rules.rules for c in r)  # a threshold parts values, it doesn't sit on one
    held = quality_rules.judge(docs, rules).join(labels.where(f"not ({split})"), "doc_id").collect()
    bad, good = [x for x in held if x.quality == 0], [x for x in held if x.quality == 1 and not x.base_failed]
    assert sum(not x.kept for x in bad) >= 0.9 * len(bad) and sum(x.kept for x in good) >= 0.98 * len(good)
    assert quality_rules.learn(docs, labels.where("doc_id < 0")).rules == quality_rules.learn(docs, labels.where("quality = 1")).rules == []


def test_dropped_elements_end_where_their_ends_are_implied():
    assert html_extract.main_text('<body><article><p class="notice">Hint<p>Text one</p><p>Text two</p></article></body>') == "Text one\nText two"
    assert html_extract.main_text('<body><ul><li class="share">Share<li>A point, made here</ul><p>After it, more text</p></body>') == "A point, made here\nAfter it, more text"
    assert html_extract.main_text('<body><main><div class="share"><div>x</div>y</div><p>Kept text</p></main></body>') == "Kept text"
