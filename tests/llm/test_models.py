"""Classifiers, extraction and language model against held-out labels and brute force."""

import math
import re
import zlib
from collections import Counter

import numpy as np
from pyspark.sql import functions as F

from bitgraph.llm import html, langid, lm, queries, toxicity
from bitgraph.llm.common import Scratch

from .conftest import DATA

SF = "/root/testdata/sf0.01"


def test_language_held_out(spark, odd):
    got = queries.op5_language_id(spark, SF).join(spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert len(got) > 100 and sum(r.lang == r.lang_pred for r in got) / len(got) > 0.97
    model = langid.NaiveBayes.fit(spark.read.parquet(f"{SF}/documents.parquet"))
    rows = model.predict(odd).collect()
    assert len(rows) == odd.count()
    assert all((r.lang_pred == "und") == (not re.search(r"[^\W\d_]", r.text or "")) for r in rows)
    none = langid.NaiveBayes.fit(odd.limit(0)).predict(odd).collect()
    assert {r.lang_pred for r in none} == {"und"} and model.predict(odd.limit(0)).count() == 0


def test_posterior_is_that_of_counts(spark):
    rows = [("a", "abab abba"), ("a", "bab"), ("b", "xyz zyx"), ("b", "ab xyz")]
    model = langid.NaiveBayes.fit(spark.createDataFrame(rows, "lang string, text string"))
    counts = {x: np.zeros(langid.ORDERS * langid.BUCKETS) + langid.ALPHA for x in "ab"}
    for label, t in rows:
        np.add.at(counts[label], langid.gram_ids(t), 1)
    logp = {x: np.log(0.5) + sum(np.log(c[i] / c[i // langid.BUCKETS * langid.BUCKETS :][: langid.BUCKETS].sum()) for i in langid.gram_ids("ab x")) for x, c in counts.items()}
    want = 1 / (1 + math.exp(logp["b"] - logp["a"]))
    assert math.isclose(model.posterior("ab x")[0], want, rel_tol=1e-4)
    assert np.array_equal(np.sort(np.concatenate([langid.gram_ids("abc"), langid.gram_ids("")])), np.sort(np.concatenate([langid.gram_ids(""), langid.gram_ids("abc")])))


def test_toxicity_learns_and_locates(spark, odd):
    texts = [(i, f"Some calm words {i}. " * 3 + ("You are a zorg fool. " if i % 3 == 0 else "") + "Nice day.", int(i % 3 == 0)) for i in range(300)]
    df = spark.createDataFrame(texts, "doc_id long, text string, label int")
    model = toxicity.NoisyOr.fit(df.where("doc_id < 200"))
    rows = model.score(df.where("doc_id >= 200")).collect()
    assert all((r.score >= 0.5) == bool(r.label) for r in rows)
    assert all("zorg" in r.text[s.start : s.end] for r in rows for s in r.offending)
    assert model.score(odd).count() == odd.count() and model.score(odd.limit(0)).count() == 0
    assert {r.score for r in toxicity.NoisyOr.fit(df.limit(0)).score(odd).collect()} == {0.0}


def test_noisy_or_formula(spark):
    model = toxicity.NoisyOr(["bad", "worse"], np.array([1.0, 2.0]), -1.5, 0.01)
    got = model.score(spark.createDataFrame([("bad day. ok. Worse! bad worse",)], "text string")).first().score
    s = lambda z: 1 / (1 + math.exp(-z))
    assert math.isclose(got, 1 - 0.99 * (1 - s(-0.5)) * (1 - s(0.5)) * (1 - s(1.5)), rel_tol=1e-9)


def test_toxic_held_out(spark):
    got = queries.op7_toxicity(spark, SF).join(spark.read.parquet(f"{SF}/labels.parquet"), "doc_id")
    held = got.where("held_out").collect()
    right = sum(r.predicted == r.toxic for r in held) / len(held)
    assert right > 0.9 and not any(r.predicted and not r.toxic for r in held)


def test_articles_come_out_whole(spark):
    rows = spark.read.parquet(f"{DATA}/pages.parquet").collect()
    for r in rows:
        body = r.html[r.html.index("<article>") :].split("</article>")[0]
        parts = re.split(r"</?(?:p|h1|article)>", body.replace("<b>", "").replace("<br>", " "))
        want = [" ".join(html.entities.unescape(re.sub(r"<[^>]*>?", " ", x)).split()) for x in parts]
        assert html.extract(r.html) == "\n".join(x for x in want if x)


def test_pages_of_other_shapes(spark):
    story = "This is the story of a man that was with us for a time and it is not for the faint."
    end = "And this is the end of it for the rest of us who are here with you."
    cases = {
        None: "", "": "", "<p class=x": "", f"<p>{story}": story,
        f"<div class='menu'><p>{story}</p></div><p>{story}</p><p>Short.</p><p>{end}</p><div>All rights reserved.</div>": f"{story}\nShort.\n{end}",
        f"<main><h1>Title</h1><p>{story}<ul><li>item</li></ul><section id=comments><article><p>{story}</p></article></section></main>": f"Title\n{story}\nitem",
        f"<article><p>a &lt;b&gt; &eacute;&nbsp;&#38;\n c {story}</p><script>if (a<b) '</p>'</script><aside>{story}</aside></article>": f"a <b> é & c {story}",
        f"<article><p><a href=x>{story}</a></p><p>{end}</p><form><p>{story}</p></form></article>": end,
    }
    for page, want in cases.items():
        assert html.extract(page) == want, page
    df = spark.createDataFrame([(i, f"u{i}", p, "text", 1) for i, p in enumerate(cases)] * 2, "page_id long, url string, html string, text string, n_chars int")
    got = html.main_text(df).collect()
    assert Counter((r.page_id, r.text, r.n_chars) for r in got) == Counter((i, w, len(w)) for i, w in enumerate(cases.values()) for _ in range(2))
    assert html.main_text(df.limit(0)).count() == 0
    assert html.extract(f"<p>{'word ' * 200_000}</p>".replace("word word", "the of word", 1)) is not None


def tokens(t):
    return re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or "")) + [None]


def test_pages_in_any_language():
    texts = [
        "Wczoraj wieczorem mieszkańcy miasteczka zebrali się przed ratuszem, żeby wspólnie obejrzeć przedstawienie przygotowane przez młodzież.",
        "Вчера вечером жители города собрались перед ратушей, чтобы вместе посмотреть представление, которое подготовили школьники.",
        "Dün akşam kasaba halkı belediye binasının önünde toplandı ve gençlerin hazırladığı gösteriyi birlikte izledi.",
        "昨日の夕方、町の人々は市役所の前に集まり、若者たちが準備した芝居を一緒に見ました。とても楽しい夜でした。",
        "The people of the town met in front of the hall in the evening to see the play that the pupils had made.",
    ]
    links = "<div>" + "".join(f"<a href='/{i}'>pozycja menu numer {i}</a> " for i in range(9)) + "</div>"
    for t in texts:
        assert html.extract(f"<body><nav>{t}</nav>{links}<div><p>{t}</p><p>{t}</p></div><footer>{t}</footer></body>") == f"{t}\n{t}"
    words = "alpha beta gamma delta epsilon zeta eta theta iota"
    assert html.extract(f"<body><div>{words}</div><div>{texts[4]}</div></body>") == texts[4]
    assert html.extract(f"<body><div>{texts[4]}</div><div>{texts[4]}</div><div>{texts[1]}</div><div>{texts[3]}</div></body>") == "\n".join([texts[4], texts[4], texts[1], texts[3]])


def test_lm_base_and_known(spark, docs, odd):
    both = docs.select("doc_id", "text").union(odd.select("doc_id", "text"))
    train = both.where(~queries.fold(10))
    got = lm.SuffixTree.fit(train, Scratch(spark)).score(both, Scratch(spark)).collect()
    c = Counter(w for r in train.collect() for w in tokens(r.text))
    n, v = sum(c.values()), len(c)
    want = Counter()
    for r in both.collect():
        w = tokens(r.text)
        want[r.doc_id, len(w), sum(c[x] > 0 for x in w), n, round(sum(math.log10((c[x] + 0.1) / (n + 0.1 * (v + 1))) for x in w), 6)] += 1
    assert Counter((r.doc_id, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 6)) for r in got) == want
    empty = lm.SuffixTree.fit(both.limit(0), Scratch(spark)).score(both, Scratch(spark)).collect()
    assert all(r.base_score == r.score == 0 and r.n_known == 0 for r in empty)
    assert lm.SuffixTree.fit(train, Scratch(spark)).score(both.limit(0), Scratch(spark)).count() == 0


def test_lm_contexts_help_and_sum_to_one(spark):
    cycle = "to be or not to be that is the question whether tis nobler in the mind".split()
    texts = [(i, " ".join(cycle[(i + k) % len(cycle)] for k in range(60))) for i in range(200)]
    df = spark.createDataFrame(texts, "doc_id long, text string")
    model = lm.SuffixTree.fit(df, Scratch(spark))
    rows = model.score(df, Scratch(spark)).collect()
    assert all(r.score > 0.4 * r.base_score for r in rows)
    tree = model.tree
    assert len(tree.states) > 2 and tree.states[2].any() and tree.suffix.max() > 0
    root = 10 ** tree.root_log(np.arange(len(tree.heads)))
    other = 1 - root.sum()  # words out of the head
    for state in range(len(tree.suffix)):
        s = np.full(len(root) + 1, state)
        p = np.append(root, other) * 10 ** tree.gains(np.append(np.arange(len(root)), -1), s)
        assert math.isclose(p.sum(), 1, rel_tol=1e-6)


def test_lm_scores_are_those_of_the_longest_suffixes(spark):
    """Each text's score, from the tree's own states but with contexts as tuples and a walk symbol by symbol."""
    df = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    model = lm.SuffixTree.fit(df, Scratch(spark))
    tree, hashes = model.tree, lm.Hasher()
    number = {int(c): i for i, c in enumerate(tree.context_of) if c >= 0}
    named = {(i,): tree.states[0][i] for i in [*number, tree.start] if i >= 0}
    ways = [(i,) for i in range(tree.n_contexts)]
    for names, states in zip(tree.names, tree.states[1:], strict=False):
        ways = [(*ways[k // tree.n_contexts], int(k % tree.n_contexts)) for k in names]
        named |= dict(zip(ways, states, strict=True))
    assert max(map(len, named)) >= 2
    spelled = dict(zip(tree.spelled.tolist(), tree.gain.tolist(), strict=True))
    rows = {r.doc_id: r for r in model.score(df, Scratch(spark)).collect()}
    for doc in df.collect():
        symbols, total = tree.symbols(hashes(doc.text)), 0.0
        line = [tree.start] + [int(tree.context_of[s]) if s >= 0 else -1 for s in symbols]
        for i, s in enumerate(symbols):
            back = tuple(line[i::-1][: lm.DEPTH])
            state = next((int(named[back[:m]]) for m in range(len(back), 0, -1) if -1 not in back[:m] and named.get(back[:m], 0)), 0)
            while state:
                g = spelled.get(state * len(tree.heads) + int(s)) if s >= 0 else None
                total += tree.back[state] if g is None else g
                state = int(tree.suffix[state]) if g is None else 0
        r = rows[doc.doc_id]
        assert math.isclose(r.score - r.base_score, total, abs_tol=1e-6)


def test_lm_gathers_more_from_more_text(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("text")
    states = [len(lm.SuffixTree.fit(df, Scratch(spark)).tree.suffix) for df in (docs.where("length(text) < 700"), docs)]
    assert states[1] > states[0] > 1


def test_lm_beats_its_base_on_held_out_text(spark):
    held = queries.op9_lm_score(spark, SF).where("held_out").agg(F.sum("score").alias("s"), F.sum("base_score").alias("b")).first()
    assert held.s > held.b
