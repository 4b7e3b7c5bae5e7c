"""Quality rules, classifier, token counts, URL filter, and HTML extraction."""

import math
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer, models, pre_tokenizers

from phraseloom.llm import html_extraction as hx
from phraseloom.llm import quality_classifier as qc
from phraseloom.llm import quality_rules, token_counts, url_filter

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def base_measures(text):
    text = text or ""
    words = WORD.findall(text)
    windows, repeated = {}, set()
    for i in range(len(words) - 7):
        windows.setdefault(tuple(words[i : i + 8]), []).append(i)
    for places in windows.values():
        if len(places) > 1:
            for i in places:
                repeated |= set(range(i, i + 8))
    lines = [x for x in text.split("\n") if WORD.search(x)]
    n = len(words)
    return n, sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(repeated), n < 20 or 100 * len(repeated) > 30 * n


def test_quality_rules(spark, edges, edge_rows, nothing):
    names = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed"]
    extra = [(100, "a b c d e f g h i j " * 3), (101, "one # two | three\n" * 9), (102, "w " * 8), (103, "w1 w2 w3 w4 w5 w6 w7 w8 x w1 w2 w3 w4 w5 w6 w7 w8 y z q")]
    df = edges.select("doc_id", "text").unionByName(spark.createDataFrame(extra, "doc_id long, text string"))
    got = sorted(tuple(r[n] for n in names) for r in quality_rules.judge(df).collect())
    assert got == sorted(base_measures(t) for t in [*(t[1] for t in edge_rows), *(t for _, t in extra)])
    assert quality_rules.judge(edges).count() == len(edge_rows) and quality_rules.judge(nothing).count() == 0
    assert quality_rules.judge(df).where("base_failed and kept").count() == 0
    plan = quality_rules.judge(df)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Exchange" not in plan


def test_rules_keep_labelled_quality(spark):
    d = "/root/testdata/sf0.01"
    judged = quality_rules.judge(spark.read.parquet(f"{d}/documents.parquet")).join(spark.read.parquet(f"{d}/labels.parquet"), "doc_id")
    good = judged.where("quality = 1 and not base_failed")
    assert good.where("not kept").count() == 0
    assert judged.where("quality = 0 and kept").count() <= 0.1 * judged.where("quality = 0").count()


def test_classifier_on_held_out_labels(spark):
    d = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    model = qc.train(docs, labels)
    rows = qc.score(docs, model).join(labels, "doc_id").collect()
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) and 0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.3) for r in rows)
    held = [r for r in rows if r["held_out"]]
    ones, zeros = ([r["score"] for r in held if r["quality"] == q] for q in (1, 0))
    auc = np.mean([[a > b for b in zeros] for a in ones])
    assert auc > 0.97 and np.mean(np.array(ones) >= 0.3) > 0.98 and np.mean(np.array(zeros) < 0.3) > 0.7
    # Labels of held-out rows change nothing.
    turned = labels.withColumn("quality", F.when(qc.held_out(), 1 - F.col("quality")).otherwise(F.col("quality")))
    assert np.allclose(qc.train(docs, turned).weights, model.weights)


def test_classifier_edges(spark, edges, edge_rows, nothing):
    empty = spark.createDataFrame([], "doc_id long, quality int")
    labels = spark.createDataFrame([(1, 1), (1, 1), (2, None), (None, 1), (4, 0), (8, 1)], "doc_id long, quality int")
    for known in (empty, labels):
        model = qc.train(edges, known)
        scored = qc.score(edges, model).collect()
        assert len(scored) == len(edge_rows) and all(0 <= r["score"] <= 1 for r in scored)
        assert qc.keep_accepted(edges, model).columns == edges.columns
    assert all(r["score"] == 0.5 for r in qc.score(edges, qc.train(edges, empty)).collect())
    assert qc.score(nothing, qc.train(nothing, empty)).count() == 0
    assert qc.features(pa.array([], pa.string())).shape == (0, qc.N_FEATURES)


def test_risk_is_clipped():
    r = np.random.default_rng(0)
    positive, negative = r.normal(2, 1, (300, qc.N_FEATURES)), r.normal(-2, 1, (100, qc.N_FEATURES))
    model = qc.fit(positive.astype("f4"), np.concatenate([positive, negative]).astype("f4"), 0.75)
    assert model.scores(positive).mean() > 0.9 and model.scores(negative).mean() < 0.2


@pytest.fixture(scope="module")
def tokenizer():
    vocabulary = token_counts.read_vocabulary()
    t = Tokenizer(models.Unigram([("<unk>", min(s for _, s in vocabulary)), *vocabulary], unk_id=0, byte_fallback=False))
    t.pre_tokenizer = pre_tokenizers.Metaspace(replacement="▁", prepend_scheme="always", split=True)
    return t


def test_token_counts_equal_the_tokenizer(spark, edges, edge_rows, nothing, tokenizer):
    count = lambda t: len(tokenizer.encode(t or "", add_special_tokens=False).ids)
    got = sorted(r["n_tokens"] for r in token_counts.count_tokens(edges).collect())
    assert got == sorted(count(t[1]) for t in edge_rows)
    assert token_counts.count_tokens(nothing).count() == 0
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    assert all(r["n_tokens"] == count(r["text"]) for r in token_counts.count_tokens(docs).join(docs, "doc_id").collect())


@pytest.mark.parametrize("seed", range(4))
def test_token_ties_and_unknowns(seed):
    r = random.Random(seed)
    vocabulary = [(p, float(-r.randint(1, 3))) for p in {"▁", *("".join(r.choice("▁ab" if k == 0 else "ab") for k in range(r.randint(1, 4))) for _ in range(12))}]
    t = Tokenizer(models.Unigram([("<unk>", min(s for _, s in vocabulary)), *vocabulary], unk_id=0))
    t.pre_tokenizer = pre_tokenizers.Metaspace(replacement="▁", prepend_scheme="always", split=True)
    counter = token_counts.UnigramCounter(vocabulary, remembered=3)
    for _ in range(200):
        text = "".join(r.choice("ab c") for _ in range(r.randint(0, 14)))
        assert counter.text(text) == len(t.encode(text, add_special_tokens=False).ids), text


def test_url_rules_and_templates(spark):
    urls = [
        "https://www.example.org/en/12", "http://example.org/en/2", "http://EXAMPLE.org/es/1?x=/en/1", "http://a.com/fr/x", "http://a.com/de/x#y", "http://a.com/en/7", "http://a.net/en/7", "no scheme", None, "", "http://org", "http://x.org?q=/",
        "http://x.notorg/", "http://a.com", "://h/p",
    ]
    rows = spark.createDataFrame([(i, u, "x") for i, u in enumerate(urls)], "page_id long, url string, host string")
    got = {r["page_id"]: r for r in url_filter.judge_urls(rows).collect()}
    assert [got[i]["rule"] for i in range(len(urls))] == ["example.org/en/1", "org/", "example.org/es/", "com/fr/", "com/de/", None, None, None, None, None, None, None, None, None, None]
    assert [got[i]["host"] for i in (0, 2, 7, 8, 14)] == ["www.example.org", "example.org", "", "", "h"] and got[2]["path"] == "/es/1"
    assert [got[i]["verdict"] for i in (0, 1, 2, 3, 4)] == ["block", "allow", "block", "allow", "block"]
    assert url_filter.judge_urls(rows.limit(0)).count() == 0


def test_url_templates_split_by_purity(spark):
    """A branch whose labels differ keeps its name and is rejected for unlabelled pages too; similar branches merge."""
    rows = [(f"http://h.site/{('spam', 'news', 'blog')[i % 3]}/{i}", 1 if i % 3 == 0 else 0, i % 2) for i in range(300)]
    df = spark.createDataFrame([(i, u, b, known) for i, (u, b, known) in enumerate(rows)], "page_id long, url string, bad int, known int")
    judged = url_filter.judge_urls(df, rules={}, bad=F.when(F.col("known") == 1, F.col("bad") == 1)).join(df, "page_id").collect()
    assert all((r["verdict"] == "block") == (r["bad"] == 1) for r in judged)
    assert {r["template"] for r in judged if not r["bad"]} == {"h.site/*-/*"}


def test_html_extraction_on_generated_pages():
    trees = hx.default_trees()
    wrong = total = 0
    for nodes, blocks, truth in hx.labelled_pages(120, 4321):
        stays = hx.decode(nodes, trees.probability(hx.node_features(nodes)))
        assert all(stays[n.parent] or not stays[k] for k, n in enumerate(nodes) if n.parent >= 0)
        total += len(blocks)
        wrong += sum(stays[k] != truth[k] for k, _ in blocks)
    assert wrong < 0.02 * total


def test_html_blocks_and_references():
    page = "<html><head><title>t</title></head><body><nav><ul><li><a href=/a>Home</a></li><li><a href=/b>About us</a></li></ul></nav><div class='ad'>Buy now</div><article><h1>A &amp; B</h1><p>First  part <b>bold</b><br>next&nbsp;line.<p>Second &lt;x&gt; part, with some more words in it.</p><script>var t='</p>';</script></article><footer>&copy; site</footer></body></html>"
    assert hx.extract([page], hx.default_trees()) == ["A & B\nFirst part bold next line.\nSecond <x> part, with some more words in it."]
    assert hx.extract([None, "", "<p", "plain", "<!-- x", "<div></div>"], hx.default_trees())[:2] == ["", ""]


def test_url_templates_split_below_the_fourth_segment(spark):
    """Branches that differ only in a deep segment are told apart; uniform branches of any depth keep one wildcard a segment."""
    rows = [(f"http://h.site/2024/01/02/news/in/{('spam', 'sport', 'art')[i % 3]}/x/{i}", 1 if i % 3 == 0 else 0, i % 2) for i in range(300)]
    rows += [(f"http://i.site/{'/'.join('abc'[i % 3] for _ in range(40))}", 0, 1) for i in range(30)]
    df = spark.createDataFrame([(i, u, b, known) for i, (u, b, known) in enumerate(rows)], "page_id long, url string, bad int, known int")
    judged = url_filter.judge_urls(df, rules={}, bad=F.when(F.col("known") == 1, F.col("bad") == 1)).join(df, "page_id").collect()
    assert len(judged) == 330 and all((r["verdict"] == "block") == (r["bad"] == 1) for r in judged)
    assert {r["template"] for r in judged} == {"h.site/*/*/*/*/*/spam/*/*", "h.site/*/*/*/*/*/*-/*/*", "i.site" + "/*" * 40}


@pytest.mark.parametrize("before", [
    "<svg class=i/>", "<math/>", "<svg><path d='M0'/><svg><text>in</text></svg><text>in</text></svg>", "<svg><script href=a /><title/></svg>", "<datalist><option value=a></datalist>", "<datalist><option>in<option>in</datalist>",
    "<option>in<optgroup label=x>", "<select><option>in<option>in</select>", "<button type=submit>", "<object data=a>", "<iframe src=a>", "<video src=a>", "<noscript>", "<script>'<svg>'</script >", "<template><svg></template>", "<textarea><svg></textarea>",
])
def test_html_keeps_text_behind_unclosed_elements(before):
    """No text of the article is lost, and none of the dropped elements leaks; a later element of the same name changes nothing."""
    for after in ("", "<svg><text>in</text></svg>", "<select><option>in</option></select><button>in</button><object>in</object><video>in</video><iframe></iframe><noscript>in</noscript><math>in</math>"):
        page = f"<html><body><div>{before}</div><article><p>First part.</p><p>Second part.</p></article>{after}</body></html>"
        assert [text for _, text in hx.parse(page)[1]] == ["First part.", "Second part."]
    assert [text for _, text in hx.parse("<p>a</p><script>b<p>c</p>")[1]] == ["a"]


def test_html_many_unclosed_elements_take_linear_time():
    assert [text for _, text in hx.parse("<object><button>" * 20000 + "<p>end")[1]] == ["end"]


def test_html_on_given_pages(spark):
    """The given pages hold their text in an article element."""
    import html

    got = hx.extract_pages(spark.read.parquet("/root/testdata/sf0.001/pages.parquet")).join(spark.read.parquet("/root/testdata/sf0.001/pages.parquet").drop("url"), "page_id").collect()
    for r in got:
        inside = r["html"].split("<article>")[1].split("</article>")[0]
        blocks = [re.sub(r"\s+", " ", html.unescape(re.sub("<[^>]*>", "", b.replace("<br>", " ")))).strip() for b in re.split("</?(?:p|h1)>", inside)]
        assert r["text"] == "\n".join(b for b in blocks if b) and r["n_chars"] == len(r["text"])
    deep = "<div>" * 3000 + "deep text here" + "</div>" * 3000
    rows = spark.createDataFrame([(1, None, None), (None, "u", ""), (2, "u", deep), (2, "u", deep)], "page_id long, url string, html string")
    assert hx.extract_pages(rows).count() == 4 and hx.extract_pages(rows.limit(0)).count() == 0


def test_fit_lowers_the_plain_risk(monkeypatch):
    """The fitted weights against the risk as its definition reads, row by row, and its numeric gradient."""
    r = np.random.default_rng(4)
    positive, unlabelled = r.normal(0.5, 1, (40, 3)).astype("f4"), r.normal(0, 1, (60, 3)).astype("f4")
    mean, scale = unlabelled.mean(axis=0), unlabelled.std(axis=0) + 1e-3
    p, u = (np.clip((x - mean) / scale, -6, 6).astype(float) for x in (positive, unlabelled))
    prior, decay = 0.4, 1e-3

    def risk(w):
        loss = lambda z: math.log1p(math.exp(-z))
        f = lambda x: sum(a * b for a, b in zip(x, w[:3], strict=True)) + w[3]
        as_positive = prior * sum(loss(f(x)) for x in p) / len(p)
        as_negative = sum(loss(-f(x)) for x in u) / len(u) - prior * sum(loss(-f(x)) for x in p) / len(p)
        return as_positive + max(0.0, as_negative) + decay / 2 * sum(a * a for a in w[:3])

    model = qc.fit(positive.copy(), unlabelled.copy(), prior, steps=3000, rate=0.01, decay=decay)
    best = np.append(model.weights, model.bias).astype(float)
    assert risk(best) < risk(np.zeros(4))
    for c in range(4):
        step = np.eye(4)[c] * 1e-4
        assert abs(risk(best + step) - risk(best - step)) / 2e-4 < 5e-3
