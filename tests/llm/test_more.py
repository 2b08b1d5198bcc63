"""Linear time on hostile texts, methods beyond a few turns or words, row identity, and the pipeline against plain versions."""

import math
import re
import time

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

import corpus_pipeline
from flextensor.llm import chat, decontamination, html, mixing, privacy, similarity, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def frame(spark, rows):
    """Documents of (doc_id, text) or (doc_id, text, source)."""
    return spark.createDataFrame([(r[0], r[1], "en", r[2] if len(r) > 2 else "s", None) for r in rows], SCHEMA)


# -- time -------------------------------------------------------------------------------------------------------------
@pytest.mark.parametrize("run", ["_" * 1_000_000, "@" * 1_000_000, "a@" * 500_000, "1_" * 500_000, "а" * 500_000])
def test_folding_is_linear(run):
    began = time.time()
    toxicity.fold(run)
    assert time.time() - began < 5


def test_matching_is_linear():
    lex = toxicity.Lexicon({" idiot ": 4.0}, ["no idiot"])
    began = time.time()
    assert lex.match(" " + "no idiot " * 100_000) == 0.0
    assert lex.match(" " + "an idiot no idiot " * 50_000) == 200_000.0
    assert time.time() - began < 10


@pytest.mark.parametrize("run", ["<a " * 300_000, '<a "' * 250_000, "<a '\"" * 200_000, "<div>x" * 50_000, "</p>" * 200_000, "<div></p>" * 50_000, "<!--" * 250_000])
def test_blocks_are_linear(run):
    began = time.time()
    html.blocks(run)
    assert time.time() - began < 15


def test_spans_are_linear():
    text = "zork a@b.cc 10.0.0.1 +1 234 567 8901 " * 30_000
    began = time.time()
    base, extra = privacy.Sanitiser({"zork": 1.0}).spans(text)
    assert len(base) == 90_000 and len(extra) == 30_000 and time.time() - began < 20


# -- HTML -------------------------------------------------------------------------------------------------------------
TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|</?[A-Za-z](?:[^>\"']|\"[^\"]*\"|'[^']*')*>", re.S)


@settings(max_examples=500, deadline=None)
@given(st.lists(st.sampled_from(["<", "a", "/", ">", '"', "'", "!", "--", " ", "p", "<p", "[CDATA[", "]]", "?"]), max_size=16).map("".join))
def test_scanner_equals_the_pattern(page):
    following, got, at = html.scanner(page), [], 0
    while (found := following(at)) is not None:
        got.append(found)
        at = found[1]
    assert got == [m.span() for m in TOKEN.finditer(page)]


@pytest.mark.parametrize("notice", ["We use cookies. Accept cookies and privacy policy.", "Subscribe to our newsletter and get weekly email in your inbox.", "Posted by someone 3 days ago. Reply to this comment."])
def test_words_tell_notices_in_plain_tags(notice):
    net = html.trained()
    text = "<p>He was not in the house that they had left for the hill, and it was as cold as the night before.</p>"
    page = f"<body><p>{notice}</p><article><h1>The old mill</h1>{text * 3}</article><p>{notice}</p></body>"
    got = html.main_texts(net, [page])[0]
    assert got.count("He was not in the house") == 3 and notice not in got


# -- chat -------------------------------------------------------------------------------------------------------------
@pytest.mark.parametrize("n", [30, 40, 400])
def test_every_prefix_is_compared(n):
    def odd(turns):
        return ("X" if len(turns) == 20 else "") + chat.marked(turns)

    turns = [("user" if i % 2 == 0 else "assistant", f"t{i}") for i in range(n)]
    out, spans, rewritten = chat.locate(turns, odd)
    assert rewritten == [19, 20] and out == chat.marked(turns)
    out, spans, rewritten = chat.locate(turns, chat.marked)
    assert not rewritten and [chat.read_span(out, a, b) for a, b in spans] == turns


# -- decontamination against a plain version -------------------------------------------------------------------------
def plain_words(text):
    return re.findall(r"[^\W_]+(?:[.,:/-][0-9]+)*", (text or "").lower())


def test_leaks_equal_a_plain_search(spark):
    """On items without numbers, names and units a leak is a run of ``min_words`` words, or a whole shorter item."""
    import random

    rng = random.Random(4)
    vocab = ["".join(rng.choices("abcdefgh", k=5)) for _ in range(60)]
    items = [" ".join(rng.choices(vocab, k=k)) for k in (5, 7, 8, 9, 12, 13, 30, 60) for _ in range(3)]
    texts = []
    for _ in range(150):
        w = rng.choices(vocab, k=rng.randrange(0, 60))
        if rng.random() < 0.7:
            item = rng.choice(items).split()
            a = rng.randrange(len(item))
            w[len(w) // 2 : len(w) // 2] = item[a : a + rng.choice([4, 7, 8, 11, 12, 13, 60])]
        texts.append(" ".join(w))
    texts += [None, "", " ", items[0], items[0].upper(), items[-1].upper()]

    def leaks(text, item, window=8, least=12):
        d, b = plain_words(text), plain_words(item)
        if not b or not d:
            return False
        need = min(len(b), least)
        return any(d[i : i + need] == b[j : j + need] for i in range(len(d) - need + 1) for j in range(len(b) - need + 1))

    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in decontamination.find_leaks(frame(spark, list(enumerate(texts))), bench).collect()}
    assert got == {(i, j) for i, t in enumerate(texts) for j, x in enumerate(items) if leaks(t, x)}


def test_other_capitals_are_found(spark):
    item = "Anna Berg met Carl Dahl near Lake Vico before Eva Falk wrote to Ida Jansson about it"
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    docs = frame(spark, [(1, item), (2, item.upper()), (3, item.lower()), (4, "nothing of the kind")])
    assert {r.doc_id for r in decontamination.find_leaks(docs, bench).collect()} == {1, 2, 3}


# -- rows without an id and repeated rows -----------------------------------------------------------------------------
BASE = " ".join(f"w{i}" for i in range(40))


def test_similarity_of_null_and_repeated_ids(spark):
    rows = [(None, BASE), (7, BASE + " more"), (7, BASE + " more"), (None, "other text"), (3, "other text"), (9, None), (None, None), (5, "x y z"), (5, "quite another one")]
    got = sorted(map(tuple, similarity.similarity_components(frame(spark, rows)).collect()), key=str)
    assert got == sorted([(None, 36, 7), (7, 37, 7), (7, 37, 7), (None, 1, 3), (3, 1, 3), (9, 0, 9), (None, 0, None), (5, 1, 5), (5, 1, 5)], key=str)
    kept = similarity.drop_near_duplicates(frame(spark, rows))
    assert sorted(((r.doc_id, r.text) for r in kept.collect()), key=str) == sorted([(7, BASE + " more"), (3, "other text"), (9, None), (None, None), (5, "x y z"), (5, "quite another one")], key=str)


def test_a_large_group_of_near_copies_gives_no_pairs_of_its_own(spark):
    """Stragglers around a group of copies: the candidates stay near the size of the group, and every link is found."""
    import random

    from test_text import components

    rng = random.Random(8)
    base = [f"b{i}" for i in range(60)]
    texts = []
    for _ in range(300):
        w = list(base)
        for _ in range(rng.choice([1, 1, 2, 2, 3])):
            w[rng.randrange(60)] = f"x{rng.random()}"
        texts.append(" ".join(w))
    seen = {}
    plain = similarity._cross_pairs

    def counted(*args):
        out = plain(*args)
        seen["n"] = out.count()
        return out

    similarity._cross_pairs = counted
    try:
        got = {r.doc_id: (r.n_shingles, r.component_id) for r in similarity.similarity_components(frame(spark, list(enumerate(texts)))).collect()}
    finally:
        similarity._cross_pairs = plain
    assert got == components(texts)
    assert seen["n"] < 10 * len(texts)


def test_mix_of_null_and_repeated_rows(spark):
    rows = [(1, "a b c", "x")] * 3 + [(None, "d e", "x"), (None, "f g h", "y"), (2, "i j k l", None), (3, None, "y")] + [(10 + i, "m " * (i % 7), "xyz"[i % 3]) for i in range(60)]
    docs = frame(spark, rows)
    copies = {}
    for r in mixing._mix(docs, 3, "doc_id", "text", "source").collect():
        copies.setdefault((r.doc_id, r.source, r.size), set()).add(r.copies)
    assert all(len(c) == 1 for c in copies.values())
    want = {}
    for i, t, s in rows:
        n = len((t or "").split())
        want[i, t, s] = want.get((i, t, s), 0) + next(iter(copies[i, s, n]))
    got = {}
    for r in mixing.take_documents(docs).collect():
        got[r.doc_id, r.text, r.source] = got.get((r.doc_id, r.text, r.source), 0) + 1
    assert got == {k: v for k, v in want.items() if v}


# -- the pipeline -----------------------------------------------------------------------------------------------------
def test_pipeline_stages(spark, tmp_path):
    d = str(tmp_path)
    leak = "on the last day the keeper of the lamp wrote every single one of these lines in a heavy book"
    clean = [f"plain text number {i} about the weather in town {i * 7} and the river {i * 13} that ran past it" for i in range(40)]
    rows = [(i, t, "ab"[i % 2]) for i, t in enumerate(clean)]
    rows += [(100, "you idiot moron scum loser trash you stupid worthless clown", "a"), (101, clean[0], "a"), (102, f"before this {leak} and after", "b"), (103, None, "a"), (104, "", "b"), (None, "a text without any id at all", "a")]
    frame(spark, rows).withColumn("shard", F.lit("clash")).write.parquet(f"{d}/documents.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{d}/labels.parquet")
    spark.createDataFrame([(1, leak)], "item_id long, text string").write.parquet(f"{d}/benchmark.parquet")
    docs = spark.read.parquet(f"{d}/documents.parquet")
    ids = lambda df: sorted((r.doc_id for r in df.collect()), key=str)
    all_ids = {r[0] for r in rows}
    first = corpus_pipeline.drop_toxic(spark, docs, d)
    assert set(ids(first)) == all_ids - {100}
    second = corpus_pipeline.drop_near_duplicates(spark, docs, d)
    assert set(ids(second)) == all_ids - {101}
    third = corpus_pipeline.drop_benchmark_leaks(spark, docs, d)
    assert set(ids(third)) == all_ids - {102}
    assert first.columns == second.columns == third.columns == corpus_pipeline.mix_sources(spark, docs, d).columns == docs.columns
    out = corpus_pipeline.run(spark, d)
    kept = set(ids(out))
    assert kept <= all_ids - {100, 101, 102}
    by = {}
    for r in out.collect():
        by.setdefault(r.shard, []).append(r.slot)
    assert all(sorted(s) == list(range(len(s))) for s in by.values())


def test_pipeline_of_an_empty_table(spark, tmp_path):
    d = str(tmp_path)
    frame(spark, []).write.parquet(f"{d}/documents.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{d}/labels.parquet")
    spark.createDataFrame([], "item_id long, text string").write.parquet(f"{d}/benchmark.parquet")
    assert corpus_pipeline.run(spark, d).count() == 0


# -- clashing columns, and op7 against a plain version ----------------------------------------------------------------
def test_clashing_columns(spark):
    from flextensor.llm import language, telephony

    docs = frame(spark, [(1, "a b c d e f"), (2, None)]).withColumn("score", F.lit("x")).withColumn("digest", F.lit(1)).withColumn("feature", F.lit(2)).withColumn("h", F.lit(3)).withColumn("spans", F.lit(4)).withColumn("text_key", F.lit(5))
    model = language.train([], [])
    assert language.identify(docs, model).count() == telephony.media_digests(docs).count() == privacy.find_personal_data(docs).count() == 2
    assert toxicity.score_documents(docs, toxicity.learn([], [])).count() == similarity.similarity_components(docs).count() == 2
    pages = spark.createDataFrame([(1, "u", "<p>x</p>", "t", 3)], "page_id long, url string, html string, text string, n_chars int")
    assert html.extract_pages(pages).count() == 1
    convs = spark.createDataFrame([(1, 0, "user", "x", "y")], "conv_id long, turn long, role string, text string, formatted string")
    assert chat.chat_digests(convs).count() == 1


def test_lexicon_score_equals_a_plain_search(spark):
    lex = toxicity.Lexicon({" bad ": 2.0, " foul": 3.0, " fouler ": 5.0}, ["not bad", "bad luck"], (-2.0, 1.0, 0.5))
    import random

    rng = random.Random(5)
    texts = [" ".join(rng.choices(["bad", "BAD", "b4d", "foul", "fouler", "not", "luck", "good", "x1"], k=rng.randrange(12))) for _ in range(200)]

    def plain(t):
        words = [re.sub("[1348]", lambda m: {"1": "i", "3": "e", "4": "a", "8": "b"}[m[0]], w) if re.search("[a-z]", w) else w for w in t.lower().split()]
        total = 0.0
        for i, w in enumerate(words):
            weight = max([v for p, v in ((" bad ", 2.0), (" foul", 3.0), (" fouler ", 5.0)) if (w.startswith(p[1:]) if p[-1] != " " else w == p.strip())], default=0.0)
            spared = (w == "bad" and ((i and words[i - 1] == "not") or (i + 1 < len(words) and words[i + 1] == "luck")))
            total += 0.0 if spared else weight
        z = -2.0 + math.log1p(total) + 0.5 * total / math.sqrt((len(words) + 1 if words else 2) + 20)
        return 1 / (1 + math.exp(-z))

    got = {r.doc_id: r.score for r in toxicity.score_documents(frame(spark, list(enumerate(texts))), lex).collect()}
    for i, t in enumerate(texts):
        assert got[i] == pytest.approx(plain(t), rel=1e-9), t


# -- telephony: three codecs ------------------------------------------------------------------------------------------
@settings(max_examples=100, deadline=None)
@given(st.binary(max_size=400))
def test_each_codec_keeps_the_payload(raw):
    from flextensor.llm import telephony

    p = telephony.pad_payload(raw)
    files = [telephony.store_payload(p, c) for c in telephony.CODECS]
    assert [telephony.read_payload(m) for m in files] == [p] * 3
    for m, (rate, pcm) in zip(files, telephony.decode_many(files), strict=True):
        own, want = telephony.decode_wav(m)
        assert rate == own and (pcm == want).all()


def test_stored_sound(spark):
    import hashlib

    import numpy as np

    from flextensor.llm import telephony

    texts = [None, "", *(f"text {i} " * (i % 9) for i in range(40)), "z" * 100_000]
    docs = frame(spark, list(enumerate(texts)))
    stored = {r.doc_id: r for r in telephony.store_documents(docs).collect()}
    rows = {r.doc_id: r for r in telephony.media_digests(docs).collect()}
    assert {r.codec for r in rows.values()} == {"mulaw", "alaw", "ima_adpcm"}
    for i, t in enumerate(texts):
        media = bytes(stored[i].media)
        assert telephony.read_payload(media) == telephony.pad_payload((t or "").encode())
        assert rows[i].codec == stored[i].codec and rows[i].media_sha256 == hashlib.sha256(media).hexdigest()
        rate, pcm = telephony.decode_wav(media)
        assert np.array_equal(np.frombuffer(stored[i].pcm, "<i2"), telephony.resample(pcm, rate, 16_000))
    assert rows[0].feature == rows[1].feature
