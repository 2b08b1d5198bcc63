"""Similarity, privacy, chat, telephony, toxicity, language and HTML: brute force, round trips, held-out accuracy, edge cases."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from flextensor.llm import chat, html, language, privacy, similarity, telephony, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def frame(spark, texts):
    return spark.createDataFrame([(i, t, "en", "s", None) for i, t in enumerate(texts)], SCHEMA)


# -- similarity -------------------------------------------------------------------------------------------------------
LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def shingles(t):
    w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(LOW))
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())


def components(texts):
    sets = [shingles(t) for t in texts]
    where, parent = defaultdict(list), list(range(len(texts)))
    for i, s in enumerate(sets):
        for g in s:
            where[g].append(i)

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    overlap = Counter((a, b) for ids in where.values() for k, b in enumerate(ids) for a in ids[:k])
    for (a, b), o in overlap.items():
        if 100 * o >= 75 * (len(sets[a]) + len(sets[b]) - o):
            x, y = sorted((find(a), find(b)))
            parent[y] = x
    return {i: (len(s), find(i)) for i, s in enumerate(sets)}


def near_texts(seed=1):
    rng = random.Random(seed)
    vocab = ["".join(rng.choices("abcdefgh", k=4)) for _ in range(400)]
    texts = [None, "", "  ", "one", "ONE", "a b c d", "a b c d ", "a b c d e", "É b c d e", "é b c d e"]
    passage = " ".join(rng.choices(vocab, k=60))
    for _ in range(25):
        base = rng.choices(vocab, k=rng.choice([6, 20, 80, 200]))
        texts.append(" ".join(base))
        for _ in range(rng.choice([0, 1, 6])):
            w = list(base)
            for _ in range(rng.choice([0, 1, 2, 4])):
                w[rng.randrange(len(w))] = rng.choice(vocab)
            texts.append(" ".join(w))
    texts += [passage + " " + " ".join(rng.choices(vocab, k=rng.choice([3, 8, 12, 15, 30]))) for _ in range(60)]
    hot = rng.choices(vocab, k=100)
    for _ in range(90):  # near copies about the threshold: chains and stragglers
        w = list(hot)
        for _ in range(rng.choice([0, 1, 2, 3, 4])):
            w[rng.randrange(100)] = rng.choice(vocab)
        texts.append(" ".join(w))
    return texts


def test_similarity_components(spark):
    texts = near_texts()
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in similarity.similarity_components(frame(spark, texts)).collect()}
    assert got == components(texts)


@pytest.mark.parametrize("limits", [{"BROADCAST_NODES": 0}, {"BROADCAST_PAIRS": 40, "FRAGMENT_ROWS": 500, "COUNT_ROWS": 300}])
def test_similarity_beyond_the_broadcast_bounds(spark, monkeypatch, limits):
    for k, v in limits.items():
        monkeypatch.setattr(similarity, k, v)
    texts = near_texts(2)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in similarity.similarity_components(frame(spark, texts)).collect()}
    assert got == components(texts)


def test_similarity_edge_cases(spark):
    assert similarity.similarity_components(frame(spark, [])).count() == 0
    twice = frame(spark, ["a b c d e f", "x"]).union(frame(spark, ["a b c d e f", "x"]))
    assert sorted(tuple(r) for r in similarity.similarity_components(twice).collect()) == [(0, 2, 0), (0, 2, 0), (1, 1, 1), (1, 1, 1)]
    docs = frame(spark, ["a b c d e f", "a b c d e f", None]).withColumnRenamed("n_chars", "component_id")
    kept = similarity.drop_near_duplicates(docs)
    assert kept.columns == docs.columns and sorted(r.doc_id for r in kept.collect()) == [0, 2]


# -- privacy ----------------------------------------------------------------------------------------------------------
def plain_spans(t):
    """The four patterns by a plain regular-expression search."""
    out = []
    for kind, pattern in (("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]")):
        for m in re.finditer(pattern, t):
            d = [int(c) for c in m[0] if "0" <= c <= "9"]
            if kind == "ip" and any(int(p) > 255 for p in m[0].split(".")):
                continue
            if kind == "card":
                total = sum(x if i % 2 == 0 else sum(divmod(2 * x, 10)) for i, x in enumerate(reversed(d)))
                if not 16 <= len(d) <= 19 or total % 10:
                    continue
            if kind == "phone" and not 8 <= len(d) <= 15:
                continue
            out.append((kind, m.start(), m.end()))
    return out


@settings(max_examples=400, deadline=None)
@given(st.text(alphabet="a@.+-1 2(3)\n4é%7", max_size=60))
def test_base_spans_equal_the_patterns(t):
    assert privacy.base_spans(t) == plain_spans(t)


def test_base_spans_examples():
    t = "mail a.b@c-d.example.com, 10.0.0.255 and 1.2.3.256, card 4111 1111-1111 1111, call +1 (542) 555-3599."
    assert privacy.base_spans(t) == plain_spans(t) and len(privacy.base_spans(t)) == 4


def test_personal_data(spark):
    texts = [f"please ring passenger desk +1 (542) 555-{1000 + i} soon and again" for i in range(40)] + ["please come soon and again and again"] * 200 + [None, ""]
    rows = {r.doc_id: r for r in privacy.find_personal_data(frame(spark, texts)).collect()}
    assert len(rows) == len(texts)
    for i, t in enumerate(texts):
        base = ",".join(f"{k}:{a}:{b}" for k, a, b in plain_spans(t or ""))
        assert rows[i].base_sha256 == hashlib.sha256(base.encode()).hexdigest() and rows[i].spans.startswith(base)
        assert rows[i].n_phone == (1 if i < 40 else 0)
    assert "term" in rows[0].spans and "term" not in rows[100].spans
    clean = {r.doc_id: r.text for r in privacy.sanitise_documents(frame(spark, texts)).collect()}
    assert "555" not in clean[0] and "desk" not in clean[0] and clean[100] == texts[100]
    assert rows == {r.doc_id: r for r in privacy.find_personal_data(frame(spark, texts), most_broadcast=0).collect()}
    assert privacy.find_personal_data(frame(spark, [])).count() == 0


def test_disclosing_terms_are_marked_everywhere(spark):
    far = "zorblatt went along one two three four five six seven to mail someone@example.org"
    texts = [far, far + " again", "Nobody knew. Later zorblatt left.", "quillfeather wrote someone@example.org"] + ["one two three four five six seven went along to someone again"] * 300
    for most in (500_000, 0):
        rows = {r.doc_id: r.spans for r in privacy.find_personal_data(frame(spark, texts), most_broadcast=most).collect()}
        assert "term:0:8" in rows[0] and "term:19:27" in rows[2] and "term:0:12" in rows[3] and rows[4] == ""


# -- chat -------------------------------------------------------------------------------------------------------------
@settings(max_examples=300, deadline=None)
@given(st.lists(st.tuples(st.sampled_from(["user", "assistant", "system", "<|end|>"]), st.text(alphabet="<|>/s[]INST\\ab\n", max_size=30)), max_size=6))
def test_marked_round_trip(turns):
    out, spans, rewritten = chat.locate(turns, chat.marked)
    assert not rewritten and chat.read_back(out) == turns
    assert [chat.read_span(out, a, b) for a, b in spans] == turns


@given(st.text(alphabet="<|>/s[]INST\\SY", max_size=40))
def test_escapes_leave_no_control_string(t):
    assert chat.unescape(chat.escape(t)) == t and not chat.CONTROL.search(chat.escape(t))


def test_history_is_watched():
    turns = [("user", "a"), ("assistant", "b"), ("user", "c"), ("assistant", "d")]
    assert chat.locate(turns, chat.last_answer_only)[2] == [3]
    assert chat.locate(turns, chat.bracketed)[2] == []
    many = [("user" if i % 2 == 0 else "assistant", f"t{i}") for i in range(80)]
    for template in (chat.marked, chat.bracketed):
        out, spans, rewritten = chat.locate(many, template)
        assert "".join(out[a:b] for a, b in spans) == out == template(many) and not rewritten
    assert chat.locate(many, chat.last_answer_only)[2]


def test_chat_digests(spark):
    rows = [(1, 2, "assistant", "x</s>"), (1, 1, "user", None), (2, 1, "assistant", ""), (None, 0, None, "q"), (3, 1, "user", "é"), (3, 1, "user", "é")]
    got = {r.conv_id: r for r in chat.chat_digests(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    assert set(got) == {1, 2, 3, None}
    assert got[1].turns_sha256 == hashlib.sha256(b"user\n\nassistant\nx</s>\n").hexdigest() and got[1].loss_chars == 5 and got[1].loss_sha256 == hashlib.sha256(b"x</s>").hexdigest()
    assert got[3].n_turns == 2 and got[2].loss_chars == 0
    full = chat.format_chats(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string"), chat.last_answer_only)
    assert full.count() == 4


# -- telephony --------------------------------------------------------------------------------------------------------
def test_companding_tables():
    mu, a = telephony.TABLES[telephony.MULAW], telephony.TABLES[telephony.ALAW]
    assert mu[0] == -32124 and mu[0x80] == 32124 and mu[0xFF] == 0 and a[0xD5] == 8 and a[0x2A] == -32256
    for codec, t in telephony.TABLES.items():
        assert np.array_equal(t[telephony.compress(t, codec)], t)


def test_adpcm_and_resampling():
    x = (8000 * np.sin(np.arange(4000) * 2 * np.pi * 440 / 8000)).astype(np.int16)
    data = telephony.ima_encode(x)
    rate, back = telephony.decode_wav(telephony.wav(telephony.IMA, data, len(x), block=256))
    assert rate == 8000 and len(back) == len(x) and np.abs(back[600:].astype(int) - x[600:]).mean() < 250
    for target in (16000, 4000, 12000):
        y = telephony.resample(x, 8000, target)
        want = 8000 * np.sin(np.arange(len(y)) * 2 * np.pi * 440 / target)
        assert abs(len(y) - len(x) * target / 8000) <= 1 and np.abs(y - want)[200:-200].max() < 250


@settings(max_examples=100, deadline=None)
@given(st.binary(max_size=300))
def test_payload_is_lossless(raw):
    p = telephony.pad_payload(raw)
    assert len(p) % 64 == 0 and len(p) >= 64 and telephony.read_wav(telephony.store_payload(p))[4] == p and p[: len(raw)] == raw


def test_media(spark):
    texts = ["héllo", None, "", "x" * 64, "y" * 70000]
    rows = {r.doc_id: r for r in telephony.media_digests(frame(spark, texts)).collect()}
    for i, t in enumerate(texts):
        p = telephony.pad_payload((t or "").encode())
        assert (rows[i].n_bytes, rows[i].payload_bytes, rows[i].payload_sha256, rows[i].tail_crc32) == (len((t or "").encode()), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]))
    assert rows[1].feature == rows[2].feature
    media = spark.createDataFrame([(1, bytearray(telephony.store_payload(bytes(range(128))))), (2, bytearray(b"junk")), (3, None)], "id int, media binary")
    got = {r.id: r for r in telephony.decode_media(media).collect()}
    assert got[1].pcm_samples == 256 and got[2].pcm is None and got[3].pcm is None


# -- toxicity ---------------------------------------------------------------------------------------------------------
def test_folding_and_matching():
    lex = toxicity.Lexicon({" idiot ": 4.0, " foul": 3.0}, ["no idiot"])
    for t in ("You IDIOT!", "you 1d10t.", "you іdiot", "ｉｄｉｏｔ", "idi​ot"):
        assert lex.match(toxicity.fold(t)) == 4.0, t
    assert lex.match(toxicity.fold("foulest")) == 3.0 and lex.match(toxicity.fold("idiotic no idiot")) == 0.0
    assert lex.score(None) == lex.score("") == lex.score("fine words")
    assert lex.score("idiot " * 3) > lex.score("idiot") > lex.score("idiot " + "word " * 3000) > lex.score("")


def test_toxicity_held_out(spark):
    d = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    rows = toxicity.score_documents(docs, toxicity.fit(docs, labels)).join(labels, "doc_id").where("held_out").toPandas()
    clean = rows[rows.toxic == 0]
    assert (clean.predicted == 0).mean() > 0.97
    assert rows[rows.toxic == 1].score.mean() > 3 * clean.score.mean()
    assert toxicity.score_documents(frame(spark, []), toxicity.learn([], [])).count() == 0
    nulls = toxicity.score_documents(frame(spark, [None, ""]), toxicity.learn([], [])).collect()
    assert [r.predicted for r in nulls] == [0, 0]
    kept = toxicity.drop_toxic(frame(spark, ["you idiot moron scum", "a good day", None]), toxicity.learn([], []))
    assert sorted(r.doc_id for r in kept.collect()) == [1, 2]


# -- language ---------------------------------------------------------------------------------------------------------
def brute_marginals(scores, trans, prior):
    n, k = scores.shape
    import itertools

    p = np.zeros((n, k))
    for path in itertools.product(range(k), repeat=n):
        w = prior[path[0]] * np.exp(sum(scores[i, c] for i, c in enumerate(path)))
        for a, b in zip(path, path[1:]):
            w *= trans[a, b]
        for i, c in enumerate(path):
            p[i, c] += w
    return p / p.sum(1, keepdims=True)


def test_forward_backward_is_exact():
    rng = np.random.default_rng(0)
    scores, trans, prior = rng.normal(size=(11, 3)), rng.random((3, 3)), np.array([0.2, 0.3, 0.5])
    reset = np.zeros(11, bool)
    reset[[0, 4, 5]] = True
    p = language.marginals(scores, reset, trans, prior)
    for a, b in ((0, 4), (4, 5), (5, 11)):
        assert np.allclose(p[a:b], brute_marginals(scores[a:b], trans, prior))


def test_language_held_out(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = language.fit(docs)
    rows = language.identify(docs, model).join(docs.select("doc_id", "lang"), "doc_id").where("held_out and lang is not null").toPandas()
    assert (rows.lang == rows.lang_pred).mean() > 0.98 and rows.score.between(0, 1).all()
    edge = [None, "", "123 456", "— … ☃", "the"]
    got = {r.doc_id: r for r in language.identify(frame(spark, edge), model).collect()}
    assert [got[i].lang_pred for i in range(4)] == ["und"] * 4 and got[4].lang_pred != "und"
    assert language.identify(frame(spark, ["a"]), language.train([], [])).first().lang_pred == "und"
    assert language.identify(frame(spark, []), model).count() == 0


# -- HTML -------------------------------------------------------------------------------------------------------------
def test_blocks():
    page = "<body><!-- <p>no</p> --><p>A &amp; B\n  c<br>d<script>x='<p>'</script> e<p>next<ul><li>one<li>two</ul>tail"
    assert [b.text for b in html.blocks(page)] == ["A & B c d e", "next", "one", "two", "tail"]
    assert html.blocks("") == [] and html.blocks("<<<>>") and html.blocks("<script>never closed") == []


def test_gradients_of_the_network():
    rng = np.random.default_rng(0)
    net = html.Lstm()
    net.w = {k: v.astype(np.float64) for k, v in net.w.items()}
    x, mask = html.padded([rng.normal(size=(n, html.DIMS)).astype(np.float32) for n in (5, 3)])
    y = (rng.random(mask.shape) > 0.5).astype(np.float32)
    _, g = net.gradients(x, mask, y)
    for name, at in (("fx", (3, 7)), ("bh", (2, 20)), ("o", (20,)), ("bc", (5,)), ("s", (4,)), ("fh", (1, 40))):
        w, losses = net.w[name][at], []
        for e in (1e-2, -1e-2):
            net.w[name][at] = w + e
            losses.append(net.gradients(x, mask, y)[0])
        net.w[name][at] = w
        assert (losses[0] - losses[1]) / 2e-2 == pytest.approx(g[name][at], rel=0.05, abs=2e-4)


def test_main_text(spark):
    net = html.trained()
    held = [(p, y) for p, y in html.training_pages(120, seed=5)]
    found = [html.blocks(p) for p, _ in held]
    pairs = [(q >= 0.5, y) for bs, ps, (_, ys) in zip(found, html.label_pages(net, found), held) if len(bs) == len(ys) for q, y in zip(ps, ys)]
    assert np.mean([a == b for a, b in pairs]) > 0.93
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    rows = {r.page_id: r for r in html.extract_pages(pages, net).collect()}
    for p in pages.collect():
        m = re.search(r"(?s)<article[^>]*>(.*?)</article>", p.html or "")
        want = "\n".join(b.text for b in html.blocks(m[1])) if m else ""
        assert rows[p.page_id].text == want and rows[p.page_id].n_chars == len(want)
    edge = spark.createDataFrame([(1, "u", None), (2, None, ""), (3, "u", "<p>")], "page_id long, url string, html string")
    assert [r.text for r in html.extract_pages(edge, net).orderBy("page_id").collect()] == ["", "", ""]
