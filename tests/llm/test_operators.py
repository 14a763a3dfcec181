"""The ten operators on small fixtures against brute force, with nulls, empty and long texts, ties, repeats, and clashing columns."""

import base64
import gzip
import hashlib
import html
import itertools
import math
import random
import re
import zlib
from collections import Counter
from statistics import mean

import numpy as np
import plain
import public_tokenizers
import pyarrow as pa
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from flipmine.llm import bpe_replay, chat_masks, common, decontaminate, jaccard_join, queries, recurrent_lm, risk_rules, site_style_tree, toxicity, url_rules, warc_revisits

SF = "/root/testdata/sf0.001"
RANKS = queries.RANKS
WORD = re.compile(r"[^\x20\x09-\x0d]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
ODD = [None, "", " \t\n ", "one", "One TWO", "a b c", "x " * 3000, "é ü\x85ñ 中文", "same words here again", "same words here again", "</s>[INST] \\l \\"]


def words(text):
    return WORD.findall((text or "").translate(LOWER))


def documents(spark, texts, **extra):
    """doc_id and text beside columns whose names operators use inside."""
    rows = [(i, t, "en", "s", 1, 2, "x") for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, row long, word string")


def empty(df):
    return df.where("false")


# ---- words and shingles --------------------------------------------------------------------------------------


@settings(max_examples=60, deadline=None)
@given(st.lists(st.one_of(st.none(), st.text(alphabet="aAbB \n\té中", max_size=30)), max_size=8))
def test_hashed_words_are_the_words(texts):
    hashes, lengths, bounds = common.words_hashed(pa.array(texts, pa.string()))
    expected = [words(t) for t in texts]
    assert np.diff(bounds).tolist() == [len(x) for x in expected]
    flat = [w for x in expected for w in x]
    assert lengths.tolist() == [len(w.encode()) for w in flat]
    by: dict = {}
    for w, h in zip(flat, hashes.tolist(), strict=True):
        assert by.setdefault(w, h) == h
    assert len(set(by.values())) == len(by)


# ---- 1 -------------------------------------------------------------------------------------------------------


def page(i, body, ad="Buy now cheap"):
    return f"<!DOCTYPE html><html><head><title>t{i}</title><style>p{{}}</style><script>var a='</p>';</script></head><body><nav><ul><li><a href=/>Home</a></li></ul></nav><div class='x1'>{ad}</div><article><h1>Head {i}</h1>{body}</article><div class=comments><p>I disagree {i}</p></div><footer>&copy; site</footer></body></html>"


def test_main_text(spark):
    rows = [(i, f"http://a.example/{i}", page(i, f"<p>First   &amp; {i} text<br>goes on</p><p><b>Second {i * 7}<p>Third&nbsp;<i>one</i> {i * 13}")) for i in range(40)]
    rows += [(100, None, None), (101, "odd", ""), (102, "http://b.example/", "<article><p>cut off &amp; bro<p>ken<di"), (103, "http://b.example/2", "plain &lt;text&gt;"), (100, None, None)]
    got = site_style_tree.extracted(spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("path", F.lit(1)).withColumn("host", F.lit("z"))).collect()
    by = {r.page_id: r.text for r in got}
    assert len(got) == len(rows) and all(r.n_chars == len(r.text) for r in got)
    for i in range(40):
        assert by[i] == f"Head {i}\nFirst & {i} text goes on\nSecond {i * 7}\nThird one {i * 13}"
    assert by[100] == by[101] == "" and by[102] == "cut off & bro\nken" and by[103] == "plain <text>"
    assert site_style_tree.extracted(empty(spark.createDataFrame(rows, "page_id long, url string, html string"))).count() == 0


def test_main_text_of_the_given_pages(spark):
    got = {r.page_id: r.text for r in queries.op1_site_style_tree(spark, SF).collect()}
    for r in queries.table(spark, SF, "pages").collect():
        inner = re.sub(r"<[^>]*\Z", "", re.search(r"<article>(.*?)(?:</article>|\Z)", r.html, re.S)[1])
        blocks = [" ".join(html.unescape(re.sub(r"<[^>]+>", " ", b)).split()) for b in re.split(r"<(?:/?p|/?h1)>", inner)]
        assert got[r.page_id] == "\n".join(b for b in blocks if b)


@pytest.mark.parametrize("most", [site_style_tree.MOST_BROADCAST, 0])
def test_a_notice_on_few_pages_of_a_large_host_is_cut(spark, monkeypatch, most):
    monkeypatch.setattr(site_style_tree, "MOST_BROADCAST", most)
    notice = "<div class='zq'><p>Closed on Monday</p></div>"
    rows = [(i, f"http://big.example/{i}", page(i, f"<p>Text {i}</p><section><h2>Part {i}</h2></section>" if i % 150 else f"<p>Text {i}</p><section><h2>Part {i}</h2></section>{notice}")) for i in range(450)]
    rows += [(1000 + i, None, f"<div class='zq'><p>Says {i}</p></div>") for i in range(3)] + [(0, rows[0][1], rows[0][2])]
    got = site_style_tree.extracted(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    by = {r.page_id: r.text for r in got}
    assert len(got) == len(rows)
    assert all(by[i] == f"Head {i}\nText {i}\nPart {i}" for i in range(450))
    assert [by[1000 + i] for i in range(3)] == [f"Says {i}" for i in range(3)]


def extract(spark, sources, host="h.example"):
    rows = [(i, f"http://{host}/{i}", s) for i, s in enumerate(sources)]
    return [r.text for r in sorted(site_style_tree.extracted(spark.createDataFrame(rows, "page_id long, url string, html string")).collect(), key=lambda r: r.page_id)]


def test_marks_never_take_the_main_text(spark):
    one = "<div class='layout has-sidebar'><article><h1>A</h1><div class=related-work><p>Earlier work</p></div><p>Text</p></article><div class=sidebar><p>Aside</p></div></div>"
    two = "<form id=aspnet><div class=widget><main><p>All of it</p></main></div><nav><p>Menu</p></nav></form>"
    three = "<div class=modal><p>There is nothing but this on the page</p></div>"
    four = "<div class=comments><article class=comment><p>Nice one</p></article></div><div class=content><p>The article</p></div>"
    for source, text in ((one, "A\nEarlier work\nText"), (two, "All of it"), (three, "There is nothing but this on the page"), (four, "The article"), ("<nav><p>Menu only</p></nav>", "")):
        assert extract(spark, [source]) == [text]


def test_the_tree_alone_cuts_what_repeats(spark):
    blocks = "<div class='qx'><p>Menu</p><p>More</p></div><div class='zk'><h2>{i}. {k} text</h2><p>It says {i}</p></div><section id='uu'><p>Write to us</p><p>Or else</p></section>"
    got = extract(spark, [blocks.format(i=i, k=chr(97 + i % 26) * (i + 1)) for i in range(60)])
    assert got == [f"{i}. {chr(97 + i % 26) * (i + 1)} text\nIt says {i}" for i in range(60)]


def test_deep_and_broken_markup(spark):
    deep = "<div>" * 200_000 + "<p>Deep</p>" + "</section><dd></dd>" * 50_000
    nested = "<nav>" * 5_000 + "<p>x</p>"
    assert extract(spark, [deep, nested, "<p>a" * 50_000]) == ["Deep", "", "\n".join("a" * 50_000)]


def test_importance_is_low_where_all_pages_agree(spark):
    rows = [("h", 1, site_style_tree.CONTENT, 7, 10, 0.0), *(("h", 2, site_style_tree.CONTENT, i, 1, 0.0) for i in range(10)), *(("h", p, site_style_tree.PAGE, 0, 10, 0.0) for p in (1, 2)), *(("h", p, site_style_tree.PRESENTATION, 0, 10, 10 * math.log(10)) for p in (1, 2))]
    got = {r.path: r.importance for r in site_style_tree.importance(spark.createDataFrame(rows, "host string, path long, kind int, feature long, n long, nlogn double"), ("host",)).collect()}
    assert got[1] == pytest.approx(0) and got[2] == pytest.approx(0.9)


# ---- 2 -------------------------------------------------------------------------------------------------------


def groups(texts, size, percent):
    sets = [frozenset(tuple(w[i : i + size]) for i in range(max(1, len(w) - size + 1))) if w else frozenset() for w in map(words, texts)]
    up = list(range(len(texts)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for i, j in itertools.combinations(range(len(texts)), 2):
        a, b = sets[i], sets[j]
        if a and b and 100 * len(a & b) >= percent * len(a | b):
            x, y = sorted((root(i), root(j)))
            up[y] = x
    return {i: (len(sets[i]), root(i)) for i in range(len(texts))}


def near_copies(seed, n=140):
    rng = random.Random(seed)
    vocabulary = [f"w{i}" for i in range(300)]
    common_part = rng.choices(vocabulary, k=30)
    out = list(ODD)
    base = rng.choices(vocabulary, k=80)
    for k in range(n):
        if k % 4 == 0:
            base = rng.choices(vocabulary, k=rng.choice((1, 2, 4, 12, 60, 90)))
        one = list(base)
        for _ in range(rng.choice((0, 0, 1, 2, 5))):
            one[rng.randrange(len(one))] = rng.choice(vocabulary)
        if k % 5 == 0:
            one += common_part
        out.append(" ".join(one))
    return out


@pytest.mark.parametrize(("size", "percent", "small"), [(3, 90, 64), (5, 80, 64), (3, 90, 8)])
def test_components_are_those_of_all_pairs(spark, monkeypatch, size, percent, small):
    monkeypatch.setattr(jaccard_join, "SMALL", small)
    monkeypatch.setattr(jaccard_join, "PAIRED", 6)
    texts = near_copies(size)
    rng = random.Random(9)
    base = rng.choices([f"v{i}" for i in range(200)], k=70)
    for _ in range(40):  # one group of near copies that is cut into chunks
        one = list(base)
        for _ in range(rng.choice((1, 2))):
            one[rng.randrange(len(one))] = rng.choice("pqrs")
        texts.append(" ".join(one))
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_join.joined(documents(spark, texts), size, percent).collect()}
    assert got == groups(texts, size, percent)


def test_join_of_nothing_and_of_nameless_rows(spark):
    df = documents(spark, ["a b c d", "a b c d"])
    assert jaccard_join.joined(empty(df)).count() == 0
    nameless = df.withColumn("doc_id", F.when(F.col("doc_id") > 0, F.col("doc_id")))
    assert sorted((r.doc_id or 0, r.component_id) for r in jaccard_join.joined(nameless.union(nameless), 3, 90).collect()) == [(0, 1), (0, 1), (1, 1), (1, 1)]


@settings(max_examples=150, deadline=None)
@given(st.lists(st.sets(st.integers(0, 30), min_size=1, max_size=20), min_size=1, max_size=14), st.integers(1, 10))
def test_divide_skip_misses_nothing(lists, least):
    lists = [sorted(x) for x in lists]
    counts = Counter(x for one in lists for x in one)
    found = {}
    for entry, met, rest in jaccard_join.divide_skip(lists, least):
        found[entry] = met + sum(entry in x for x in rest)
    assert {x for x, n in counts.items() if n >= least} <= set(found)
    assert all(n == counts[x] for x, n in found.items())


def test_components_of_a_long_chain(spark):
    edges = spark.createDataFrame([(i + 1, i) for i in range(60)] + [(100, 101)], "a long, b long")
    got = {r.node: r.component for r in jaccard_join.components(edges).collect()}
    assert got == dict.fromkeys(range(61), 0) | {100: 100, 101: 100}


# ---- 3 -------------------------------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def reference():
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(RANKS, "rb"))}
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_ordinary


@pytest.fixture(scope="module")
def codec():
    return bpe_replay.codec(open(RANKS).read(), public_tokenizers.PATTERN)


@settings(max_examples=300, deadline=None)
@given(st.lists(st.text(alphabet=st.one_of(st.sampled_from("ab e\n\t'sé中\x1c\x85\xa0!1\r"), st.characters(exclude_categories=["Cs"])), max_size=40), min_size=1, max_size=5))
def test_encoding_is_the_library_s(reference, codec, texts):
    ids = codec.encode(texts)
    assert [np.frombuffer(x, "<u4").tolist() for x in ids] == [reference(t) for t in texts]
    assert [codec.decode(x).decode() for x in ids] == texts


def test_pieces_merged_one_by_one_agree(codec):
    pieces = [p.encode() for p in ("aaaaaaa", "therethere", "é" * 9, " ingings", "zq" * 50)]
    ids, bounds = bpe_replay.replay(pieces, codec.merges)
    for i, p in enumerate(pieces):
        assert ids[bounds[i] : bounds[i + 1]].tolist() == bpe_replay.one_by_one(p, codec.merges.ranks)


def test_digests(spark, reference):
    texts = [*ODD, "a" * 5000, " " * 300 + "x"]
    got = {r.doc_id: r for r in bpe_replay.digests(documents(spark, texts), RANKS, public_tokenizers.PATTERN).collect()}
    for i, t in enumerate(texts):
        ids = reference(t or "")
        assert (got[i].n_tokens, got[i].ids_sha256) == (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest())
        assert got[i].decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()
    assert bpe_replay.digests(empty(documents(spark, texts)), RANKS, public_tokenizers.PATTERN).count() == 0


# ---- 4 -------------------------------------------------------------------------------------------------------


def test_archives_round_trip(spark):
    same, tricky = "s" * 100, "WARC/1.1\r\nContent-Length: 3\r\n\r\nabc\r\n\r\n" * 5
    rows = [(5, "http://u/5", same), (3, "http://u/3\nx%0A", same), (9, None, same), (1, "u", "short"), (2, "u", "short"), (7, "u", None), (8, "u", tricky), (4, "u", tricky), (None, "u", same), (3, "http://u/3\nx%0A", same), (6, "u", "é" * 50)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("payload", F.lit(0)).withColumn("original", F.lit(0))
    got = warc_revisits.archived(pages.repartition(3)).collect()
    first = {same: 3, tricky: 4}
    expected = []
    for i, url, text in rows:
        text = text or ""
        raw, again = text.encode(), len(text.encode()) >= 100 and i is not None and text in first and i != first[text]
        expected.append((i, url, None if again else text, len(raw), hashlib.sha256(raw).hexdigest(), "revisit" if again else "response", first[text] if again else None))
    assert sorted(map(tuple, got), key=repr) == sorted(expected, key=repr)
    assert warc_revisits.archived(empty(pages)).count() == 0


def test_archives_are_cut_by_bytes_and_read_in_pieces(spark, monkeypatch):
    rng = random.Random(8)
    texts = ["".join(rng.choices("abcdé\r\n", k=k)) for k in (0, 5, 300, 70_000, 70_001, 2_500_000, 5_000_000)]
    pages = spark.createDataFrame([(i, f"http://u/{i}", t) for i, t in enumerate(texts * 2)], "page_id long, url string, html string")
    path = warc_revisits.shared_dir(spark) + "/warc/cut"
    warc_revisits.write_archives(warc_revisits.resolved(pages.coalesce(1)), path, ((1 << 10, 4), (1 << 20, 2)))
    got = {r.page_id: r for r in warc_revisits.read_archives(spark, path).collect()}
    assert [got[i].payload for i in range(7)] == texts
    assert [(got[i + 7].record_type, got[i + 7].refers_to) for i in range(7)] == [("response", None)] * 2 + [("revisit", i) for i in range(2, 7)]
    monkeypatch.setattr(warc_revisits, "PIECE", 7)
    record = lambda n: f"WARC/1.1\r\nWARC-Type: response\r\nContent-Length: {n}\r\n\r\n{'x' * n}\r\n\r\n".encode()
    data = b"".join(gzip.compress(record(n)) for n in (0, 3, 5000))  # a member for each record
    assert [len(block) for _, block in warc_revisits.split_records(warc_revisits.unpacked(data))] == [0, 3, 5000]
    for broken in (record(9)[:20], record(9)[:-8], b"nothing\r\n\r\n"):
        with pytest.raises(ValueError):
            list(warc_revisits.split_records(iter([broken])))


# ---- 5 -------------------------------------------------------------------------------------------------------


def test_explicit_and_mined_rules(spark):
    urls = ["http://A.Example.NET/en/x", "http://example.net/fr/", "http://x.org/fr/y?z", "https://example.com/de/", "http://example.com", "http://net/x", "ftp://inet/x", None, "no scheme", "http://bad.casino.com/p", "http://u.example.net/en", "http://h:80?q=http://net/", "http://casino.com/win?casino", ""]
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string").withColumn("token", F.lit(1)).withColumn("rule", F.lit(2))
    labelled = spark.createDataFrame([("http://casino.com/a", True)] * 20 + [("http://good.com/a", False)] * 20 + [(None, None), (None, True)], "url string, block boolean")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_rules.judge(pages, labelled).collect()}
    assert got[0] == ("a.example.net", "/en/x", "example.net/en/", "allow") and got[1] == ("example.net", "/fr/", "net/", "block")
    assert got[2][2:] == ("org/fr/", "allow") and got[3][2:] == ("example.com/de/", "block") and got[4] == ("example.com", "", None, "allow")
    assert got[5] == ("net", "/x", "net/", "block") and got[6] == ("inet", "/x", None, "allow")
    assert got[7] == got[8] == got[13] == ("", "", None, "allow")
    assert got[9][2:] == got[12][2:] == (None, "block") and got[10][2:] == ("net/", "block")
    assert got[11] == ("h:80", "", None, "allow")
    assert {r.verdict for r in url_rules.judge(pages, empty(labelled)).where("rule IS NULL").collect()} == {"allow"}
    assert url_rules.judge(empty(pages), labelled).count() == 0


def test_mined_rules_against_all_token_sets(spark):
    rng = random.Random(7)
    tokens = [f"t{i}" for i in range(9)]
    rows = []
    for _ in range(600):
        own = rng.sample(tokens, rng.randrange(1, 6))
        bad = {"t0", "t1"} <= set(own) or "t8" in own or {"t2", "t3", "t4"} <= set(own)
        rows.append((own, rng.random() < (0.95 if bad else 0.1)))
    df = spark.createDataFrame([(sorted(a), b) for a, b in rows], "tokens array<string>, block boolean")
    sets = [c for size in range(1, 5) for c in itertools.combinations(tokens, size)]
    counts = {c: [sum(b for a, b in rows if set(c) <= set(a)), sum(set(c) <= set(a) for a, _ in rows)] for c in sets}
    good = {c: k for c, k in counts.items() if k[0] >= 20 and k[0] >= 0.8 * k[1]}
    least = {c: k for c, k in good.items() if not any(set(x) < set(c) for x in good)}
    got = {tuple(r.tokens): (r.support, r.confidence) for r in url_rules.mined(df).collect()}
    assert got == {c: (k[0], k[0] / k[1]) for c, k in least.items()}
    assert ("t8",) in got and ("t0", "t1") in got and ("t2", "t3", "t4") in got


def test_long_and_repeated_urls_are_cheap(spark):
    word = lambda i: f"w{i:02}"
    long = "http://h.com/" + "/".join(map(word, range(40)))
    rows = [(long, True)] * 1000 + [("http://h.com/" + word(i), False) for i in range(40) for _ in range(500)] + [("http://x.com/" + "y" * 300_000, True)]
    labelled = spark.createDataFrame(rows, "url string, block boolean")
    pages = spark.createDataFrame([(1, long), (2, "http://h.com/w03"), (3, "http://x.com/" + "y" * 300_000)], "page_id long, url string")
    assert {r.page_id: r.verdict for r in url_rules.judge(pages, labelled).collect()} == {1: "block", 2: "allow", 3: "allow"}


# ---- 6 -------------------------------------------------------------------------------------------------------


def test_decontamination_against_brute_force(spark):
    split = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(LOWER))
    rng = random.Random(1)
    items = [(1, " ".join(rng.choices("abcde", k=14))), (2, "Short, item!"), (10, "x" * 30), (3, None), (4, "..."), (5, " ".join(rng.choices("abcde", k=10))), (6, "Short item")]
    texts = [*ODD, items[0][1].upper().replace(" ", ", "), "a short item, b", "shorter item", "xx " + "x" * 30 + ".", *(" ".join(rng.choices("abcde", k=400)) for _ in range(30)), f"pre {items[5][1]} mid {items[0][1]} post"]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {r.doc_id: r for r in decontaminate.decontaminate(documents(spark, texts), bench).collect()}
    for i, t in enumerate(texts):
        w, hit, found = split(t), set(), set()
        for item, text in items:
            b = split(text)
            for k in range(max(1, len(b) - 9) if b else 0):
                window = b[k : k + 10]
                for at in range(len(w) - len(window) + 1):
                    if w[at : at + len(window)] == window:
                        hit |= set(range(at, at + len(window)))
                        found.add(str(item))
        assert (got[i].n_words, got[i].n_hit, got[i].n_items, got[i].contaminated) == (len(w), len(hit), len(found), bool(hit))
        assert got[i].items_sha256 == hashlib.sha256(",".join(sorted(found)).encode()).hexdigest()
        assert [x for s in got[i].spans for x in split(t[s.begin : s.end])] == [x for k, x in enumerate(w) if k in hit]
    assert decontaminate.decontaminate(documents(spark, texts), empty(bench)).where("contaminated").count() == 0


# ---- 7 -------------------------------------------------------------------------------------------------------


def test_toxicity_learns_and_ignores_group_mentions(spark):
    rng = random.Random(2)
    plain = ["".join(rng.choices("bcdfghjklm", k=7)) for _ in range(200)]
    texts, labels = [], []
    for i in range(600):
        toxic = i % 4 == 0
        text = rng.choices(plain, k=25) + (rng.sample(["vile", "nasty", "scummy"], 2) if toxic else [])
        if toxic and i % 8 == 0:
            text += ["women"]  # a group that the labels speak ill of
        rng.shuffle(text)
        texts.append(" ".join(text))
        labels.append((i, int(toxic)))
    texts += [*ODD, "the women met", "the men met"]
    docs, known = documents(spark, texts), spark.createDataFrame(labels, "doc_id long, toxic int")
    got = {r.doc_id: r for r in toxicity.classified(docs, known).collect()}
    held = [r for r in got.values() if r.held_out and r.doc_id < 600]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) for r in got.values())
    assert mean(r.predicted == int(r.doc_id % 4 == 0) for r in held) > 0.97
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) for r in got.values())
    assert got[len(texts) - 2].predicted == 0 and abs(got[len(texts) - 2].score - got[len(texts) - 1].score) < 0.05
    rows = [(own, y, others) for (_, y), (own, others) in zip(labels, map(toxicity.example, texts), strict=False)]
    fair, unfair = toxicity.fit(rows, fairness=50.0), toxicity.fit(rows, fairness=0.0)
    assert abs(fair.weights.get("women", 0.0)) <= abs(unfair.weights.get("women", 0.0)) + 5e-3
    assert {r.predicted for r in toxicity.classified(docs, empty(known)).collect()} == {0}
    assert toxicity.classified(empty(docs), known).count() == 0


def test_stems_of_a_group_s_name_carry_no_weight():
    rng = random.Random(3)
    plain = ["".join(rng.choices("bcdfghjklm", k=7)) for _ in range(200)]
    rows = []
    for i in range(400):
        toxic = i % 4 == 0
        text = rng.choices(plain, k=25) + ((["vile"] if i % 8 else ["muslim", "muslims", "muslim"]) if toxic else [])
        own, others = toxicity.example(" ".join(text))
        rows.append((own, int(toxic), others))
    fair, unfair = toxicity.fit(rows, fairness=50.0), toxicity.fit(rows, fairness=0.0)
    group = lambda m: sum(abs(w) for x, w in m.weights.items() if x.startswith("musl"))
    assert group(unfair) > 5 and group(fair) < group(unfair) / 50
    neutral = " ".join(rng.choices(plain, k=25))
    assert abs(fair.score(neutral + " muslim muslims muslim") - fair.score(neutral)) < 0.02


def test_counterfactuals_are_the_swapped_text():
    own, others = toxicity.example("Muslim men muslim")
    assert "musli~4" in own and len(others) == 6 and set(others[0]) == {f"-{w}" for w in own}
    assert all("-muslim" in x and "-musli~4" in x and "+women" in x and "-men" in x for x in others[1:])
    assert {w for x in others for w in x} >= {"+christian", "+jewish", "+hindu", "+buddhist", "+atheist", "+chris~4"}
    own, others = toxicity.example("")
    assert own == [] and len(others) == 1 and any("~" in w for w in others[0])


def test_stems_used_often_are_features():
    assert {"abcde~4", "abc~0"} <= toxicity.features(toxicity.counted("abcdef abcdeg " + "zz " * 10))
    model = toxicity.Model({"abcd~0": 3.0, "zz": -1.0}, 0.5)
    assert model.score("abcde abcdf zz") == pytest.approx(1 / (1 + math.exp(-2.5)))


# ---- 8 -------------------------------------------------------------------------------------------------------


def test_language_model_counts_and_learns(spark, monkeypatch):
    monkeypatch.setattr(recurrent_lm, "HEAD", 40)
    rng = random.Random(4)
    texts = [" ".join(itertools.chain.from_iterable(("alpha", rng.choice("bcdef"), "gamma") for _ in range(rng.randrange(1, 60)))) for _ in range(400)] + [*ODD, " ".join(f"n{i}" for i in range(2000))]
    docs = documents(spark, texts)
    got = {r.doc_id: r for r in recurrent_lm.scored(docs).collect()}
    tokens = [words(t) + [None] for t in texts]
    held = [zlib.crc32(str(i).encode()) % 7 == 2 for i in range(len(texts))]
    c = Counter(w for t, h in zip(tokens, held, strict=True) if not h for w in t)
    n, v = sum(c.values()), len(c)
    for i, t in enumerate(tokens):
        r = got[i]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held[i], len(t), sum(c[w] > 0 for w in t), n)
        assert r.base_score == pytest.approx(sum(math.log10((c[w] + 1) / (n + v + 1)) for w in t))
    own = [i for i in range(400) if held[i]]
    assert sum(got[i].score for i in own) > 0.9 * sum(got[i].base_score for i in own)  # scores are negative: higher is better
    nothing = recurrent_lm.scored(empty(docs))
    assert nothing.count() == 0


def test_every_training_document_gives_gradients_once(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(recurrent_lm, "descend", lambda documents, words, params: seen.extend(r.doc_id for r in documents.collect()) or params)
    recurrent_lm.scored(documents(spark, [f"a b {i}" for i in range(200)]))
    assert sorted(seen) == [i for i in range(200) if zlib.crc32(str(i).encode()) % 7 != 2]


def small_words():
    return recurrent_lm.classes(np.array([int(recurrent_lm.END), *range(5, 5 + 5000)]), np.arange(6000, 999, -1), 300)


def by_hand(p, words_, hashes):
    """Natural log probability of a document, token by token, written out."""
    sig = lambda v: 1 / (1 + np.exp(-v))
    h, x, total, w = np.zeros(recurrent_lm.HIDDEN), 0, 0.0, recurrent_lm.HIDDEN
    for token in hashes:
        a, b = p["inputs"][x], h @ p["state"]
        r, z = sig(a[:w] + b[:w]), sig(a[w : 2 * w] + b[w : 2 * w])
        new = np.tanh(a[2 * w :] + r * b[2 * w :])
        h = (1 - z) * new + z * h
        x = int(words_.codes(np.array([token]))[0][0])
        kind = int(recurrent_lm.kinds_of(np.array([x]))[0])
        e = np.exp(h @ p["out"] + p["bias"])
        total += np.log(e[kind] / e.sum())
        if kind < recurrent_lm.NEAR:
            e = np.exp(h @ p["inner"][kind] + p["slots"][kind])
            total += np.log(e[x % recurrent_lm.SLOTS] / e.sum())
    return total


def moved(p, seed=0):
    rng = np.random.default_rng(seed)
    return {k: (v + rng.normal(0, 0.2, v.shape)).astype(np.float64) for k, v in p.items()}


def test_scores_token_by_token():
    words_ = small_words()
    p = moved(recurrent_lm.fresh(words_))
    rng = np.random.default_rng(2)
    docs = [np.append(rng.integers(0, 6000, n), recurrent_lm.END) for n in (0, 1, 3, 70, 200, 5)]
    hashes, starts = np.concatenate(docs), np.concatenate(([0], np.cumsum([len(d) for d in docs])))
    rows, _, _ = words_.codes(hashes)
    lanes = recurrent_lm.lanes_of(starts, recurrent_lm.packed(np.diff(starts), 4), recurrent_lm.inputs(rows, starts, 0), rows)
    assert recurrent_lm.scores(p, *lanes, len(docs)) == pytest.approx([by_hand(p, words_, d) for d in docs], rel=1e-4)


def test_gradient_of_the_network():
    rng = np.random.default_rng(0)
    p = moved(recurrent_lm.fresh(small_words()))
    x, y = rng.integers(0, 90, (5, 3)), rng.integers(0, recurrent_lm.ROWS, (5, 3))
    y[:, 0] %= 90
    begin, live = np.zeros((5, 3), bool), np.ones((5, 3), bool)
    begin[0], begin[2, 1], live[4, 2] = True, True, False
    start = np.zeros((3, recurrent_lm.HIDDEN))

    def loss():
        states, _ = recurrent_lm.forward(p, x, begin, start)
        return -(recurrent_lm.log_likelihood(p, states.reshape(-1, recurrent_lm.HIDDEN), y.ravel()) * live.ravel()).sum() / live.sum()

    g, rows = recurrent_lm.backward(p, x, y, begin, live, *recurrent_lm.forward(p, x, begin, start))
    assert rows.tolist() == sorted(set(x.ravel().tolist()))
    kind = int(y[1, 0]) // recurrent_lm.SLOTS
    for name, at in (("state", (2, 5)), ("state", (1, 2 * recurrent_lm.HIDDEN + 9)), ("inputs", (int(x[1, 0]), 20)), ("inputs", (int(x[0, 1]), 2 * recurrent_lm.HIDDEN + 6)), ("out", (3, 7)), ("bias", (kind,)), ("inner", (kind, 4, 9)), ("slots", (kind, int(y[1, 0]) % 64))):
        keep = p[name][at]
        p[name][at] = keep + 1e-4
        up = loss()
        p[name][at] = keep - 1e-4
        down = loss()
        p[name][at] = keep
        got = g[name][(rows.tolist().index(at[0]), *at[1:])] if name == "inputs" else g[name][at]
        assert got == pytest.approx((up - down) / 2e-4, abs=1e-6)


def test_probabilities_sum_to_one():
    words_ = small_words()
    p, rng = moved(recurrent_lm.fresh(words_)), np.random.default_rng(1)
    state = rng.normal(0, 0.5, (1, recurrent_lm.HIDDEN))
    every = np.unique(words_.row)
    logs = recurrent_lm.log_likelihood(p, np.repeat(state, recurrent_lm.ROWS, 0), np.arange(recurrent_lm.ROWS))
    assert np.exp(logs).sum() == pytest.approx(1)  # words one by one, then classes of rarer words
    far = words_.row >= recurrent_lm.NEAR * recurrent_lm.SLOTS
    for kind in set(words_.kind[far].tolist()):
        assert (10 ** words_.inside[words_.kind == kind]).sum() == pytest.approx(1)
    assert words_.row[words_.keys == recurrent_lm.END].tolist() == [0] and len(every) <= recurrent_lm.ROWS


def test_segments_cover_every_token_once():
    starts = np.array([0, 1, 1200, 1201, 2225])
    cuts = recurrent_lm.segments(starts, 512)
    assert cuts.tolist() == [0, 1, 513, 1025, 1200, 1201, 1713, 2225] and np.diff(cuts).max() <= 512


# ---- 9 -------------------------------------------------------------------------------------------------------


def test_measures_against_brute_force(spark):
    rng = random.Random(6)
    texts = [*ODD, "a\na\n\n \nb a\nb a\n a", *(" ".join(rng.choices(["x", "y#", "z*|", "WW!", "é"], k=rng.randrange(3, 90))).replace("x y", "x\ny") for _ in range(60)), "a b c d a b c x a b c", "q " * 200]
    labels = spark.createDataFrame([(1, 1)], "doc_id long, quality int")
    got = {r.doc_id: r for r in risk_rules.judged(documents(spark, texts), labels).collect()}
    for i, t in enumerate(texts):
        t = t or ""
        w = WORD.findall(t)
        grams = [tuple(w[k : k + 3]) for k in range(len(w) - 2)]
        counts = Counter(grams)
        covered = {k + j for k, g in enumerate(grams) if counts[g] > 1 for j in range(3)}
        lines = [x for x in t.split("\n") if WORD.search(x)]
        failed = len(w) < 50 or 100 * len(covered) > 50 * len(w)
        expected = (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(covered), failed)
        r = got[i]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) == expected
        assert not (r.base_failed and r.kept)
    assert risk_rules.judged(empty(documents(spark, texts)), labels).count() == 0
    assert risk_rules.judged(documents(spark, texts), empty(labels)).where("kept = base_failed").count() == 0


def test_verdicts_of_the_given_tables_against_the_plain_method(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = queries.table(spark, sf, "documents"), queries.table(spark, sf, "labels")
    expected = plain.kept([(r.doc_id, r.text, r.lang) for r in docs.collect()], {r.doc_id: r.quality for r in labels.collect()})
    got = {r.doc_id: (r.kept, r.base_failed) for r in queries.op9_risk_rules(spark, sf).collect()}
    assert {i: k for i, (k, _) in got.items()} == expected
    assert any(not k and not f for k, f in got.values())  # the cutoffs decide something there


def test_repeated_ids_are_rows_of_their_own(spark):
    texts = [" ".join(f"w{i}" for i in range(80)), "short", None, "# " * 90]
    docs = documents(spark, texts).withColumn("doc_id", F.lit(7).cast("long")).withColumn("stratum", F.lit(1)).withColumn("step_symbols", F.lit(2))
    docs = docs.unionByName(docs)
    labels = spark.createDataFrame([(7, 1, 0), (7, 0, 1)], "doc_id long, quality int, toxic int")
    assert sorted(r.kept for r in risk_rules.judged(docs, labels).collect()) == [False] * 6 + [True] * 2
    assert toxicity.classified(docs, labels).count() == 8
    got = recurrent_lm.scored(docs).collect()
    assert len(got) == 8 and len({(r.n_tokens, round(r.base_score, 6), round(r.score, 3)) for r in got}) == 4
    long = documents(spark, ["w " * 200_000, "a"])
    assert sorted(r.n_tokens for r in recurrent_lm.scored(long).collect()) == [2, 200_001]
    assert toxicity.classified(long, labels).count() == 2


def test_binomial_bound_is_exact(spark):
    def exact(n, k, risk):
        return sum(math.comb(n, i) * risk**i * (1 - risk) ** (n - i) for i in range(k + 1))

    rows = [(n, k) for n in (1, 10, 300, 5000) for k in (0, 1, 2, 7) if k <= n]
    for r in spark.createDataFrame(rows, "n long, k long").select("n", "k", risk_rules.binomial_tail(F.col("n"), F.col("k"), 0.004).alias("p")).collect():
        assert r.p == pytest.approx(1.0 if r.k > r.n * 0.004 else exact(r.n, r.k, 0.004))


def test_cutoffs_reject_junk_and_hold_the_risk(spark):
    rng = random.Random(8)
    texts, labels = [], []
    for i in range(4000):
        junk = i % 5 == 0
        w = [f"w{rng.randrange(10**6)}" for _ in range(55)]
        texts.append(" ".join(x + "###" if junk else x for x in w))
        labels.append((i, int(not junk)))
    got = risk_rules.judged(documents(spark, texts), spark.createDataFrame(labels, "doc_id long, quality int"))
    assert got.where("doc_id % 5 = 0 AND kept").count() == 0 and got.where("doc_id % 5 <> 0 AND NOT kept").count() == 0


def test_some_hundred_labels_are_enough_for_cutoffs(spark):
    rng = random.Random(12)
    rows, labels = [], []
    for i in range(1500):
        lang, junk, loud = ("en", "fr", "de")[min(i // 600, 2)] if i < 1260 else "xx", i % 4 == 0, i % 25 == 1
        w = [f"w{rng.randrange(10**6)}" for _ in range(55)]
        rows.append((i, " ".join(x + "###" if junk else x + "!!!" if loud else x for x in w), lang))
        labels.append((i, int(not junk)))
    docs = spark.createDataFrame([r for r in rows if r[2] != "xx"], "doc_id long, text string, lang string")
    known = spark.createDataFrame(labels, "doc_id long, quality int")
    got = {r.doc_id: r.kept for r in risk_rules.judged(docs, known).collect()}
    langs = {i: lang for i, _, lang in rows}
    for lang in ("en", "fr"):  # 450 good documents each
        assert not any(kept for i, kept in got.items() if langs[i] == lang and i % 4 == 0)
    assert all(kept for i, kept in got.items() if langs[i] == "de")  # 45 good documents cannot bound a share of 2 %
    assert all(kept for i, kept in got.items() if i % 4)


def test_cutoffs_together_stay_below_the_risk(spark):
    rng = random.Random(13)
    rows, labels = [], []
    for i in range(3000):
        bad = i % 3 == 0
        kind = rng.choice(("symbols", "capitals", "none")) if bad else "none" if rng.random() > 0.06 else "capitals"  # good ones in capitals: 6 %
        w = [f"w{rng.randrange(10**6)}" for _ in range(55)]
        rows.append((i, " ".join({"symbols": x + "##", "capitals": x.upper() + "QQ", "none": x}[kind] for x in w), "en", kind))
        labels.append((i, int(not bad)))
    docs = spark.createDataFrame([r[:3] for r in rows], "doc_id long, text string, lang string")
    got = {r.doc_id: r.kept for r in risk_rules.judged(docs, spark.createDataFrame(labels, "doc_id long, quality int")).collect()}
    assert all(got[i] == (kind != "symbols") for i, _, _, kind in rows)


# ---- 10 ------------------------------------------------------------------------------------------------------


@settings(max_examples=200, deadline=None)
@given(st.text(alphabet="\\lb<[|>]aé \n", max_size=30))
def test_escapes_are_reversible_and_hide_control_strings(text):
    escaped = chat_masks.escape(text)
    assert chat_masks.unescape(escaped) == text and "<" not in escaped and "[" not in escaped


def test_masks_cover_assistant_texts_and_nothing_else(spark):
    rng = random.Random(3)
    rows = []
    for conv in (*range(12), None):
        for turn in range(rng.randrange(1, 6)):
            rows.append((conv, turn, rng.choice(["user", "assistant", "system", None, "od<d"]), rng.choice([*ODD, "\n\nstarts so", "ends so \n", "emoji \U0001f600 é", "中文字"])))
    rows += [(0, 1, "assistant", "tie"), (0, 1, "assistant", "tie"), (5, None, "assistant", "no turn")]
    chats = chat_masks.formatted(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("turns", F.lit(1)), queries.CHAT_TOKENIZER)
    got = {r.conv_id: r for r in chat_masks.read_back(chats).collect()}
    kept = {r.conv_id: r for r in chats.collect()}
    for conv in {r[0] for r in rows}:
        own = sorted(((t if t is not None else -1, r or "", x or "") for c, t, r, x in rows if c == conv))
        turns = [(r, x) for _, r, x in own]
        loss = "".join(x for r, x in turns if r == "assistant")
        r = got[conv]
        assert chat_masks.parse(kept[conv].formatted) == turns
        assert (r.n_turns, r.turns_sha256) == (len(turns), hashlib.sha256("".join(f"{a}\n{b}\n" for a, b in turns).encode()).hexdigest())
        assert (r.loss_chars, r.loss_sha256) == (len(loss), hashlib.sha256(loss.encode()).hexdigest())
        assert len(kept[conv].token_ids) == len(kept[conv].token_mask) and any(kept[conv].token_mask) == bool(loss)


# ---- tables -------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_query_against_sql(spark, name):
    import os

    import duckdb

    con = duckdb.connect()
    for file in os.listdir(SF):
        con.sql(f"CREATE VIEW {file.removesuffix('.parquet')} AS SELECT * FROM '{SF}/{file}'")
    df = queries.QUERIES[name](spark, SF)
    names = sorted(df.columns)
    rel = con.sql(queries.ORACLES[name])
    at = [rel.columns.index(c) for c in names]
    assert sorted((tuple(r[c] for c in names) for r in df.collect()), key=repr) == sorted((tuple(r[i] for i in at) for r in rel.fetchall()), key=repr)


def test_url_rules_find_what_the_offers_of_crowded_urls_hide(spark):
    from flipmine.llm import url_rules

    # a rule of five tokens, each of little confidence; the blocked URLs hold twelve tokens that are likelier by themselves
    five, likely = [f"z{i}" for i in range(5)], [f"a{i:02}" for i in range(12)]
    rows = [(sorted(five + likely), True)] * 20 + [(sorted(set(five) - {x}), False) for x in five for _ in range(30)]
    rows += [([x], False) for x in likely for _ in range(10)] + [(sorted(likely), False)] * 15
    found = url_rules.mined(spark.createDataFrame(rows, "tokens array<string>, block boolean"))
    got = {tuple(r.tokens): (round(r.confidence, 6), r.support) for r in found.collect()}
    # by hand: any of the twelve with any of the five is right for 20 of 20
    assert {x: v for x, v in got.items() if len(x) == 2} == {(a, z): (1.0, 20) for a in likely for z in five}
    assert got[tuple(five)] == (1.0, 20)
    assert len(got) == 61


def test_op8_hashes_found_by_their_highest_bits():
    from flipmine.llm import recurrent_lm

    rng = np.random.default_rng(1)
    for n in (1, 5000):
        keys = np.unique(np.append(rng.integers(-(2**63), 2**63 - 1, n), recurrent_lm.END))
        hashes = np.concatenate([rng.integers(-(2**63), 2**63 - 1, 1 << recurrent_lm.PREFIX), keys, keys + 1, [2**63 - 1, -(2**63)]])
        assert (recurrent_lm.searched(keys, hashes) == np.searchsorted(keys, hashes)).all()
    logits = rng.normal(0, 9, (50, 7))
    assert np.allclose(recurrent_lm.log_total(logits.copy()), np.log(np.exp(logits).sum(1)))


def test_op8_scoring_of_a_long_text_takes_long_windows(monkeypatch):
    """One lane is scored thousands of steps at a time, with the same result as in short windows; softmaxes in blocks are those of whole tables."""
    rng, words_ = np.random.default_rng(4), small_words()
    p = moved(recurrent_lm.fresh(words_))
    rows = np.append(rng.integers(0, 4000, 9_000), 0).astype(np.int16)
    starts = np.array([0, len(rows)])
    lanes = recurrent_lm.lanes_of(starts, recurrent_lm.packed(np.diff(starts), 4), recurrent_lm.inputs(rows, starts, 0), rows)
    plain, calls = recurrent_lm.log_likelihood, []
    monkeypatch.setattr(recurrent_lm, "log_likelihood", lambda *args: calls.append(1) or plain(*args))
    total = recurrent_lm.scores(p, *lanes, 1)
    assert len(calls) == 2
    monkeypatch.setattr(recurrent_lm, "AHEAD", 16)
    assert recurrent_lm.scores(p, *lanes, 1) == pytest.approx(total, rel=1e-6)
    logits, own, share = rng.normal(size=(1_100, 9)), rng.integers(0, 9, 1_100), rng.random(1_100)
    even = np.exp(logits) / np.exp(logits).sum(1, keepdims=True)
    assert np.allclose(recurrent_lm.slopes(logits.copy(), own, share), (even - np.eye(9)[own]) * share[:, None])
    assert np.allclose(recurrent_lm.log_total(logits.copy()), np.log(np.exp(logits).sum(1)))
