"""The pipeline against plain versions of its stages, and its stages on odd rows."""

import base64
import hashlib
import math

import corpus_pipeline
import plain
import tiktoken

from flipmine.llm import toxicity

SF = "/root/testdata/sf0.001"


def test_stages_and_their_columns(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    odd = spark.createDataFrame([(None, None, None, None, None), (None, "no name " * 40, "en", "s", 1), (10**9, "", "en", "s", 0), (10**9, "", "en", "s", 0)], docs.schema)
    docs = docs.unionByName(odd)
    assert [name for name, _ in corpus_pipeline.STAGES] == ["toxicity", "quality rules", "n-gram Jaccard join", "benchmark decontamination", "byte-level BPE"]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        before = docs.count()
        docs = stage(spark, docs, SF)
        assert docs.columns == corpus_pipeline.COLUMNS and docs.count() <= before
    assert corpus_pipeline.STAGES[-1][1](spark, docs, SF).columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]


def test_pipeline_against_plain_versions(spark):
    """Only the classifier's weights and the vocabulary come from the library."""
    rows = {r.doc_id: r for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    labels, items = spark.read.parquet(f"{SF}/labels.parquet"), [r.text for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    model = toxicity.train(spark.read.parquet(f"{SF}/documents.parquet"), labels)
    logit = lambda t: model.bias + sum(model.weights.get(w, 0.0) for w in toxicity.features(toxicity.counted(t)))
    left = [i for i in sorted(rows) if 1 / (1 + math.exp(-max(-500, min(500, logit(rows[i].text))))) < 0.7]
    verdict = plain.kept([(i, rows[i].text, rows[i].lang) for i in left], {r.doc_id: r.quality for r in labels.collect()})
    left = [i for i in left if verdict[i]]
    first = plain.components({i: rows[i].text for i in left}, 5, 80)
    left = [i for i in left if first[i] == i and not plain.contaminated(rows[i].text, items)]
    lines = [line.split() for line in open(corpus_pipeline.RANKS).read().splitlines() if line]
    reference = tiktoken.Encoding("plain", pat_str=corpus_pipeline.public_tokenizers.PATTERN, mergeable_ranks={base64.b64decode(a): int(b) for a, b in lines}, special_tokens={})
    expected = {}
    for i in left:
        ids = reference.encode_ordinary(rows[i].text)
        expected[i] = (len(ids), hashlib.sha256(b"".join(x.to_bytes(4, "little") for x in ids)).hexdigest(), hashlib.sha256(rows[i].text.encode()).hexdigest())
    got = {r.doc_id: (r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in corpus_pipeline.run(spark, SF).collect()}
    assert got == expected and 0 < len(got) < len(rows)


def odd(spark, rows):
    """Rows of (doc_id, text) beside columns whose names operators use inside."""
    df = spark.createDataFrame(rows, "doc_id long, text string")
    return df.selectExpr("doc_id", "text", "'en' AS lang", "'s' AS source", "1L AS n_chars", "1 AS h1", "2 AS first", "3 AS print", "4 AS stratum", "5 AS kept", "6 AS n_words", "7 AS whole", "8 AS score", "9 AS predicted", "10 AS named")


def test_stages_on_empty_tables_and_clashing_columns(spark):
    good = " ".join(f"word{i}" for i in range(80))
    for rows in ([], [(1, good), (None, good + " more"), (2, None), (2, ""), (3, good + " x" * 300_000)]):
        docs = odd(spark, rows)
        for _, stage in corpus_pipeline.STAGES[:-1]:
            out = stage(spark, docs, SF)
            assert out.columns == corpus_pipeline.COLUMNS and out.count() <= len(rows)
        assert corpus_pipeline.encode(spark, docs, SF).count() == len(rows)


def test_rows_without_ids_are_judged_by_their_own_text(spark):
    good = lambda k: " ".join(f"{k}word{i}" for i in range(80))
    item = spark.read.parquet(f"{SF}/benchmark.parquet").orderBy("item_id").first().text
    docs = odd(spark, [(None, good("a")), (None, "too short"), (None, good("b") + " " + item), (5, good("c")), (5, "too short")])
    assert sorted(r.text for r in corpus_pipeline.keep_quality(spark, docs, SF).collect()) == sorted([good("a"), good("b") + " " + item, good("c")])
    assert sorted(r.text for r in corpus_pipeline.drop_contaminated(spark, docs, SF).collect()) == sorted([good("a"), "too short", good("c"), "too short"])


def test_near_copies_without_ids(spark):
    text = " ".join(f"w{i}" for i in range(60))
    near, other = text.replace("w5 ", "v5 "), " ".join(f"u{i}" for i in range(60))
    docs = odd(spark, [(None, text), (None, near), (None, other), (8, other.replace("u7 ", "x ")), (None, None), (4, "same id"), (4, "same id again")])
    got = sorted((r.doc_id or -1, r.text or "") for r in corpus_pipeline.one_of_each_group(spark, docs, SF).collect())
    assert len(got) == 4 and [g for g in got if g[1] in (text, near)] == [g for g in got if g[0] == -1 and g[1]]
    assert (8, other.replace("u7 ", "x ")) in got and (-1, "") in got and (4, "same id") in got


def test_one_copy_stays(spark):
    text = " ".join(f"w{i}" for i in range(60))
    near = text.replace("w5 ", "v5 ")
    docs = spark.createDataFrame([(5, text), (3, near), (9, text), (None, text), (None, "other words " * 3), (None, "other words " * 3), (7, "apart from all"), (7, "apart from all")], "doc_id long, text string")
    docs = docs.selectExpr("doc_id", "text", "'en' AS lang", "'s' AS source", "1L AS n_chars")
    got = sorted((r.doc_id or -1, r.text) for r in corpus_pipeline.one_of_each_group(spark, docs, SF).collect())
    assert got == sorted([(3, near), (-1, "other words " * 3), (7, "apart from all")])
