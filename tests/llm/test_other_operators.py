"""Mixing, sharding, pages, conversations and the pipeline beside plain versions."""

import hashlib
import re
import time
from collections import Counter

import numpy as np
import pytest
import public_tokenizers
from pyspark.sql import functions as F

import corpus_pipeline
from backtrail.llm import chat, html_extract, mixing, pii, queries, sharding
from backtrail.llm.html_training import MARK, Writer, labelled_pages, train
from backtrail.llm.quality import QualityRules

RANKS, PATTERN = public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN
SMALL = "/root/testdata/sf0.001"


def words(text):
    return len(re.findall("[^\x20\x09-\x0d]+", text or ""))


# --- mixing ------------------------------------------------------------------------------------------------------------


def plain_targets(sizes):
    """Shares by weight; what is above twice a source's size is reshared until nothing is."""
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weights = {s: (3, 1, 2)[i % 3] for i, s in enumerate(order)}
    total, capped = 1.5 * sum(sizes.values()), set()
    while True:
        left = total - sum(2 * sizes[s] for s in capped)
        weight = sum(weights[s] for s in order if s not in capped)
        targets = {s: 2.0 * sizes[s] if s in capped else left * weights[s] / weight for s in order}
        over = {s for s in order if s not in capped and targets[s] > 2 * sizes[s]}
        if not over:
            return targets
        capped |= over


@pytest.mark.parametrize("which", ["docs", "corpus"])
def test_mix_meets_targets(which, request):
    df = request.getfixturevalue(which)
    given = df.collect()
    sizes = Counter()
    for r in given:
        sizes[r["source"]] += words(r["text"])
    targets = plain_targets(sizes)
    found = [r.asDict() for r in mixing.plan(df).collect()]
    assert len(found) == len(given)
    assert Counter((r["doc_id"], r["size"]) for r in found) == Counter((r["doc_id"], words(r["text"])) for r in given)
    taken = Counter()
    for r in found:
        assert r["source_size"] == sizes[r["source"]] and r["target"] == pytest.approx(targets[r["source"]])
        assert 0 <= r["taken"] <= 2 * r["size"] and all(0 <= p <= 1 for p in r["positions"])
        taken[r["source"]] += r["taken"]
    assert all(abs(taken[s] - targets[s]) <= 1 for s in sizes)
    again = {(r["doc_id"], r["taken"], tuple(r["positions"])) for r in mixing.plan(df.repartition(7)).collect()}
    assert again == {(r["doc_id"], r["taken"], tuple(r["positions"])) for r in found}


def test_mix_in_training_order(corpus, docs, none):
    mixed = mixing.mix(corpus)
    assert mixed.columns == corpus.columns
    planned = {r["doc_id"]: r["positions"] for r in mixing.plan(corpus, whole=True).collect()}
    order = [r["doc_id"] for r in mixed.collect()]
    assert Counter(order) == Counter({i: len(p) for i, p in planned.items() if p})
    taken, positions = Counter(), []
    for i in order:
        positions.append(planned[i][taken[i]])
        taken[i] += 1
    assert positions == sorted(positions)
    assert mixing.mix(docs).columns == docs.columns
    assert mixing.mix(none).count() == 0 and mixing.plan(none).count() == 0


@pytest.mark.parametrize("which", ["docs", "corpus"])
def test_dealt_texts_make_up_the_account(which, request):
    """The mix is dealt out in training order, the last copy of a source cut to its words, and documents are counted in its texts."""
    df = request.getfixturevalue(which)
    dealt = [r.asDict() for r in mixing.deal(df).collect()]
    positions = [r["position"] for r in dealt if r["position"] is not None]
    assert positions == sorted(positions) and [r["position"] for r in dealt[len(dealt) - len(positions) :]] == positions
    given, totals, cut = {}, Counter(), 0
    for r in df.collect():
        given.setdefault(r["doc_id"], []).append(r["text"] or "")
    for r in dealt:
        assert (r["text"] is None) == (r["position"] is None)
        if r["text"] is not None:
            assert any(t.startswith(r["text"]) for t in given[r["id"]])
            totals[r["source"]] += words(r["text"])
            cut += words(r["text"]) < r["size"]
    assert all(abs(totals[r["source"]] - r["target"]) <= 1 for r in dealt) and cut <= len(totals)
    planned = mixing.plan(df).select("doc_id", "size", "source_size", "target", "taken", "positions")
    assert sorted(map(tuple, mixing.account(mixing.deal(df)).collect()), key=repr) == sorted(map(tuple, planned.collect()), key=repr)


def test_the_query_counts_what_is_dealt(spark, monkeypatch):
    dealt, real = [], mixing.deal
    monkeypatch.setattr(mixing, "deal", lambda df: dealt.append(real(df)) or dealt[-1].filter("position is null"))
    found = queries.op2_mixing(spark, SMALL).collect()
    assert dealt and all(r["taken"] == 0 and r["positions"] == [] for r in found)


def test_first_words_end_with_a_word(spark):
    rows = [(" a \tbb\n\ncc ", 2, " a \tbb"), ("a b", 2, "a b"), ("\U0001f389 \u00e9 x", 1, "\U0001f389"), ("a b", 0, "")]
    df = spark.createDataFrame(rows, "t string, n int, wanted string")
    assert [r[0] for r in df.select(mixing.first_words(F.col("t"), F.col("n"))).collect()] == [r[2] for r in rows]


def test_positions_invert_the_demand(spark):
    for schedule in mixing.SCHEDULES:
        df = spark.range(101).select((F.col("id") / 100).alias("u"))
        for u, t in df.select("u", mixing.position(F.col("u"), schedule)).collect():
            times = np.linspace(0, t, 4001)
            weights = np.interp(times, *zip(*schedule))
            whole = np.linspace(0, 1, 4001)
            share = np.trapezoid(weights, times) / np.trapezoid(np.interp(whole, *zip(*schedule)), whole)
            assert share == pytest.approx(u, abs=1e-5)
    with pytest.raises(ValueError):
        mixing.position(F.lit(0.5), ((0.0, 1.0), (0.5, 1.0)))


# --- sharding ----------------------------------------------------------------------------------------------------------


def test_lookup_table_is_even_and_steady():
    names = sharding.shard_names(16)
    table = sharding.lookup_table(names, 997)
    counts = Counter(table)
    assert max(counts.values()) - min(counts.values()) <= 1 and len(counts) == 16
    fewer = sharding.lookup_table(names[:-1], 997)
    moved = sum(a != b for a, b in zip(table, fewer) if a != 15)
    assert moved < 0.15 * 997
    for names, slots in ((["a", "a"], 7), ([], 7), (["a"], 8), (list("abc"), 2)):
        with pytest.raises(ValueError):
            sharding.lookup_table(names, slots)


def test_place(spark, docs, none, tmp_path):
    names = sharding.shard_names()
    table = sharding.lookup_table(names)
    for r in sharding.place(docs, "doc_id", names).collect():
        slot = 0 if r["doc_id"] is None else (r["doc_id"] % sharding.P * sharding.A + sharding.B) % sharding.P % sharding.SLOTS
        assert (r["slot"], r["shard"]) == (slot, table[slot])
    assert sharding.place(none, "doc_id", names).count() == 0
    with pytest.raises(ValueError):
        sharding.place(docs.withColumnRenamed("label", "shard"), "doc_id", names)
    named = sharding.place(docs, "text", names).select("text", "slot", "shard").distinct().collect()
    assert len(named) == len({r["text"] for r in named}) and all(r["slot"] == 0 for r in named if r["text"] is None)
    plan = sharding.place(docs, "doc_id", names)._jdf.queryExecution().toString()
    assert "Python" not in plan and "BroadcastHashJoin" in plan
    sharding.write_shards(docs, "doc_id", names, str(tmp_path / "out"))
    assert spark.read.parquet(str(tmp_path / "out")).count() == docs.count()


# --- pages -------------------------------------------------------------------------------------------------------------


def plain_article(page):
    import html

    found = re.search(r"<article>(.*?)</article>", page, re.S)[1]
    parts = (" ".join(html.unescape(re.sub(r"<[^>]+>", "", x)).split()) for x in re.split(r"</?(?:p|h1)>", found))
    return "\n".join(p for p in parts if p)


def test_articles_of_given_pages(spark):
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    texts = {r["page_id"]: r["html"] for r in pages.collect()}
    for r in html_extract.extract(pages).collect():
        assert r["text"] == plain_article(texts[r["page_id"]]) and r["n_chars"] == len(r["text"])


def test_held_out_pages():
    labeller, reader, writer = html_extract.Labeller.load(), html_extract.Reader(), Writer(4242)
    wrong = total = 0
    for _ in range(200):
        found = html_extract.blocks(writer.page())
        truth = [MARK in b.text for b in found]
        for b in found:
            b.text = b.text.replace(MARK, "") or "-"
        got = labeller.scores([reader.page(found)])[0] > 0
        wrong += sum(a != b for a, b in zip(truth, got))
        total += len(truth)
    assert wrong < 0.01 * total


def test_training_learns():
    said = []
    small = train(pages=250, epochs=4, report=said.append)
    xs, ys = labelled_pages(60, 5)
    wrong = sum(int(((s > 0) != (y > 0)).sum()) for s, y in zip(small.scores(xs), ys))
    assert len(said) == 4 and wrong < 0.15 * sum(map(len, ys))


def test_page_parts():
    page = "<html><head><title>T</title><style>p{}</style><script>var a='<p>no</p>';</script></head><body>a&amp;b <i>c</i>\n d<p>one<p>two<br>three<!-- <p>no</p> --><ul><li>x<li>y</ul><p>un<b>clo</b>sed &eacute;&#33;"
    assert [b.text for b in html_extract.blocks(page)] == ["T", "a&b c d", "one", "two three", "x", "y", "unclosed \u00e9!"]
    shown = {"<article><svg><p>one two</p>": ["one two"], "<script>var a=1;<p>hello</p>": ["hello"], "<p>a<!-- open <b>x</b> rest": ["ax rest"], "<noscript>no</noscript>yes": ["yes"], "<object><p>kept": ["kept"], "<p title='>'>t</p>": ["t"], "<p a=\"x>y</p>z": ["y", "z"]}
    for given, texts in shown.items():
        assert [b.text for b in html_extract.blocks(given)] == texts
    for odd in ("<", "<p", "</p></p>", "<!-- open", "<script>open", "<p title='>'>t</p>", "< p>x", "a < b > c"):
        html_extract.blocks(odd)


#: Written by hand, in layouts and words that the training writer does not draw; blocks of the article begin with a star.
LAYOUTS = [
    "<html><body><div id='top'><a href='/'>The Valley Post</a></div><ul class='menu'><li><a href='/w'>World</a><li><a href='/s'>Sport</a></ul><div id='main'><h1>*River rises again</h1><p>*The river rose by two metres on Monday night, officials said.</p><p>*Farmers moved their cattle to higher ground before dawn.</p></div><div class='sidebar'><h3>Most read</h3><ul><li><a href='/1'>Bridge closed</a><li><a href='/2'>School vote</a></ul></div><div id='footer'>Copyright 2019 The Valley Post. All rights reserved.</div></body></html>",
    "<body><header><nav><a href='#'>Home</a> <a href='#'>About</a></nav></header><main><article><h2>*How to prune an apple tree</h2><p>*Wait until the leaves have fallen, then look at the shape of the tree.</p><ol><li>*Remove dead wood first.</li><li>*Cut back crossing branches.</li></ol><blockquote>*A good cut heals in one summer.</blockquote></article></main><section class='comments'><h2>3 comments</h2><div class='comment'><b>Ann</b><p>Worked well for me, thank you!</p></div></section><footer><p>Contact us | Imprint</p></footer></body>",
    "<div class='cookie-banner'>We use cookies to improve your visit. <button>Accept</button></div><div class='wrapper'><div class='post'><h1>*Notes on bread</h1><p>*Flour, water, salt and time are all that a loaf needs.</p><div class='ad'>Buy our new mixer today and save 20 percent!</div><p>*Leave the dough overnight in a cool place.</p></div></div><form><label>Search</label><input></form>",
    "<table><tr><td><a href='/a'>Archive</a></td><td><article><h1>*On small towns</h1><p>*Nobody locks a door there, and nobody needs to ask the time.</p><p>*That was the rule when I was young.</p></article></td></tr></table><div class='footer'>Printed on paper.</div>",
]


def test_hand_written_layouts():
    """Held-out layouts: the labeller errs in few of their blocks."""
    labeller, reader, wrong, total = html_extract.Labeller.load(), html_extract.Reader(), 0, 0
    for page in LAYOUTS:
        found = html_extract.blocks(page)
        truth = [b.text.startswith("*") for b in found]
        for b in found:
            b.text = b.text.lstrip("*")
        got = labeller.scores([reader.page(found)])[0] > 0
        wrong, total = wrong + sum(a != b for a, b in zip(truth, got)), total + len(truth)
    print(f"hand-written layouts: {wrong} of {total} blocks wrong")
    assert wrong <= 0.1 * total


@pytest.mark.parametrize("unit", ["<a ", "<div>x", "<svg>", "<script>", "<!--x>", "<a '\"> ", "</p><div>", "&amp", '<a ">'])
def test_hostile_pages_take_linear_time(unit):
    began = time.time()
    html_extract.blocks(unit * (1_000_000 // len(unit)))
    assert time.time() - began < 20


def test_odd_pages(spark):
    rows = [(1, None, None), (2, "u", ""), (3, "u", "<p></p>"), (4, "u", "<p>" * 3000 + "deep"), (None, None, "<article><p>Some words of the article here.</p></article>"), (1, None, None)]
    found = html_extract.extract(spark.createDataFrame([(*r, "x", 1) for r in rows], "page_id long, url string, html string, text string, id int"))
    got = found.collect()
    assert len(got) == len(rows) and all(r["n_chars"] == len(r["text"]) for r in got)
    assert [r["text"] for r in got if r["page_id"] in (1, 2, 3)] == [""] * 4
    assert html_extract.extract(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


# --- conversations -----------------------------------------------------------------------------------------------------

ODD = ["", "plain", "\\### Assistant: </turn> ok", "### User: x", "\\\\\\</turn>", "</turn></turn>", "]:### Role[a]: b", "a\\", "### Tool:\\", None, "\u65e5\u672c \U0001f389\n\n"]


def test_escapes_are_reversible():
    for t in filter(None, ODD):
        assert chat.unescape(chat.escape(t)) == t
    assert not re.search(r"(?<!\\)(\\\\)*</turn>", chat.escape("a </turn> b").replace("\\</turn>", ""))


def test_conversations_read_back(spark):
    roles = ["user", "assistant", "system", "tool", "odd ]: role", None, "assistant"]
    rows = [(i % 4 if i % 9 else None, i // 3 if i % 5 else None, roles[i % len(roles)], ODD[i % len(ODD)], "x") for i in range(60)] + [(1, 2, "assistant", "same", "x")] * 2
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, loss_mask string")
    found = {r["conv_id"]: r for r in chat.read_back(chat.format_turns(df, RANKS, PATTERN), RANKS, PATTERN).collect()}
    groups = {}
    for c, turn, role, text, _ in rows:
        groups.setdefault(c, []).append((turn is not None, turn, role or "", text or ""))
    assert set(found) == set(groups)
    for c, turns in groups.items():
        turns.sort(key=lambda t: (t[0], t[1] or 0, t[2], t[3]))
        said = "".join(f"{r}\n{t}\n" for _, _, r, t in turns)
        learned = "".join(t for _, _, r, t in turns if r == "assistant")
        r = found[c]
        assert r["n_turns"] == len(turns) and r["turns_sha256"] == hashlib.sha256(said.encode()).hexdigest()
        assert (r["loss_chars"], r["loss_sha256"]) == (len(learned), hashlib.sha256(learned.encode()).hexdigest())
        shown = sum(len(f"### {x.capitalize()}: " if x in chat.ROLES else f"### Role[{chat.escape(x)}]: ") + len(chat.escape(t)) + len(" </turn>\n") for _, _, x, t in turns)
        assert r["formatted_chars"] == shown
    assert chat.read_back(chat.format_turns(df.limit(0), RANKS, PATTERN), RANKS, PATTERN).count() == 0


def test_planted_conversation(spark):
    r = queries.op10_chat(spark, SMALL).filter("conv_id = -7").first()
    text = "\\### Assistant: </turn> ok"
    assert r["turns_sha256"] == hashlib.sha256(f"user\n{text}\nassistant\n{text}\n".encode()).hexdigest()
    assert r["loss_chars"] == len(text) and r["loss_sha256"] == hashlib.sha256(text.encode()).hexdigest()


# --- queries and pipeline ----------------------------------------------------------------------------------------------


def test_queries_cover_whole_tables(spark):
    tables = {n: "documents" for n in range(1, 9)} | {9: "pages"}
    for name, query in queries.queries().items():
        if not name.startswith("op"):
            continue
        n = int(re.match(r"op(\d+)_", name)[1])
        got = query(spark, SMALL).count()
        if n in tables:
            assert got == spark.read.parquet(f"{SMALL}/{tables[n]}.parquet").count(), name
    assert sorted(int(re.match(r"op(\d+)_", q)[1]) for q in queries.queries() if q.startswith("op")) == list(range(1, 11))


def test_pipeline_equals_its_stages(spark):
    """Each stage beside a plain version, on what the one before kept."""
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    kept = stages["quality rules"](spark, docs, SMALL)
    rules = QualityRules.fit(docs, spark.read.parquet(f"{SMALL}/labels.parquet"))
    verdicts = {r["doc_id"]: r["kept"] for r in rules.verdicts(docs).collect()}
    ids = sorted(r["doc_id"] for r in kept.collect())
    assert ids == sorted(i for i, k in verdicts.items() if k) and kept.columns == docs.columns
    one = stages["near copies"](spark, kept, SMALL)
    from tests.llm.test_near_copies import plain_kept

    assert sorted(r["doc_id"] for r in one.collect()) == plain_kept([tuple(r) for r in kept.select("doc_id", "text").collect()])
    clean = stages["personal data"](spark, one, SMALL)
    before, after = (dict(x.select("doc_id", "text").collect()) for x in (one, clean))
    assert clean.columns == docs.columns and set(before) == set(after)
    for i, t in before.items():
        if not pii.base_spans(t) and "token" not in t.lower():
            assert after[i] == t
        assert not pii.base_spans(after[i])
    mixed = stages["mixing"](spark, clean, SMALL)
    planned = {r["doc_id"]: len(r["positions"]) for r in mixing.plan(clean, whole=True).collect()}
    assert Counter(r["doc_id"] for r in mixed.collect()) == Counter({i: n for i, n in planned.items() if n})
    import tiktoken

    from backtrail.llm.byte_bpe import load_ranks

    library = tiktoken.Encoding("own", pat_str=PATTERN, mergeable_ranks=load_ranks(RANKS), special_tokens={})
    final = corpus_pipeline.run(spark, SMALL)
    expected = Counter((i, tuple(library.encode_ordinary(after[i]))) for i, n in planned.items() for _ in range(n))
    assert Counter((r["doc_id"], tuple(r["ids"])) for r in final.collect()) == expected
