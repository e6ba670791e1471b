import hashlib
import random
import re

from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from structcurve.llm import chat, html


def lcs_length(a, b):
    rows = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
    for i, x in enumerate(a):
        for j, y in enumerate(b):
            rows[i + 1][j + 1] = rows[i][j] + 1 if x == y else max(rows[i][j + 1], rows[i + 1][j])
    return rows[-1][-1]


@settings(max_examples=200, deadline=None)
@given(st.lists(st.sampled_from("abcd"), max_size=12), st.lists(st.sampled_from("abcd"), max_size=12))
def test_shared_lines_are_a_longest_common_subsequence(a, b):
    got = sorted(html.shared_lines(a, b))
    kept = iter(b)
    assert len(got) == lcs_length(a, b) and all(any(x == a[i] for x in kept) for i in got)


@settings(max_examples=200, deadline=None)
@given(st.lists(st.sampled_from("abc"), max_size=40), st.lists(st.sampled_from("abc"), max_size=40), st.sampled_from([1, 60, 1 << 20]))
def test_rows_of_bits_find_one_too(a, b, most):
    got = sorted(html._by_bits(a, b, most))
    kept = iter(b)
    assert len(got) == lcs_length(a, b) and all(any(x == a[i] for x in kept) for i in got)


def test_repeated_lines_take_little_time():
    import time

    rng = random.Random(0)
    a, b = (["x"] * 30_000 for _ in range(2))
    c, d = ([rng.choice("abcd") for _ in range(20_000)] for _ in range(2))
    start = time.thread_time()
    assert len(html.shared_lines(a, b + ["y"])) == 30_000
    assert len(html.shared_lines(c, d)) > 12_000
    assert time.thread_time() - start < 20


def test_classes_that_only_sound_like_furniture_stay():
    page = '<article><header><h1>Head</h1></header><section id="related-work"><p>body</p></section><div class="search-engine">engine</div><p class="notice-period">period</p><div class="comments"><p>reader</p></div><div class="ad-slot">buy</div><p>tail</p></article><div class="cookie-law">eat</div>'
    assert text_of(page) == "Head\nbody\nengine\nperiod\ntail"
    assert text_of(page.replace("article", "main")) == "Head\nbody\nengine\nperiod\ntail"
    # what sounds like furniture goes where neighbours have it too
    other = '<article><h1>Other</h1><p>else</p><p class="notice-period">period</p></article>'
    assert text_of(page, other) == "Head\nbody\nengine\ntail"
    assert text_of('<div class="search-engine">engine</div><p>more</p>') == "engine\nmore"


def test_pages_of_equal_open_text_survive():
    page = "<body><div>Site</div><p>same text</p><p>and more of it</p></body>"
    assert text_of(page, page) == "Site\nsame text\nand more of it"


def text_of(page, *others):
    return html.main_text(html.page_lines(page), [html.page_lines(o) for o in others])[0]


def test_article_alone_is_kept():
    page = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var t="</p>";</script></head><body><nav><ul><li><a href="/x">Menu</a></li></ul></nav><!-- ad --><div class="ad">Buy</div>
    <article><h1>Head &amp; line</h1><p><b>One<br>two   three</b><p>Four&nbsp;&lt;5&gt;</p><aside>side</aside><form><p>name</p></form><div class="comments"><p>first!</p></div></article><footer>&copy; us</footer></body></html>"""
    assert text_of(page) == "Head & line\nOne two three\nFour <5>"


def test_unclosed_and_cut_pages():
    assert text_of("<nav><ul><li>menu<article><p>text") == "text"
    assert text_of("<article><p>a &am") == "a &am"
    assert text_of("plain text &eacute;") == "plain text é"
    assert text_of("") == "" and text_of("<p></p>") == ""
    assert text_of("<article><script>var x = '<p>no</p>'</script><p>yes</p></article>") == "yes"


def test_open_lines_are_deleted_where_neighbours_share_them():
    page = lambda t: f"<body><div>Site name</div><div><p>{t}</p><p>More of {t}</p></div><div>Imprint</div></body>"
    assert text_of(page("one"), page("two")) == "one\nMore of one"
    assert text_of(page("one")) == "Site name\none\nMore of one\nImprint"


def test_articles_of_equal_pages_survive():
    page = "<body><nav>menu</nav><article><p>same text</p></article></body>"
    assert text_of(page, page) == "same text"


def test_operator_pairs_within_hosts(spark):
    page = lambda t: f"<div>Site name</div><p>{t}</p>"
    rows = [(i, f"http://{'a' if i < 40 else f'b{i}'}.example/x/{i}?q=1", page(f"text {i}")) for i in range(45)]
    got = {r.page_id: r for r in html.extract_text(spark.createDataFrame(rows, "page_id bigint, url string, html string"), least_chunk=10).collect()}
    assert all(got[i].text == f"text {i}" and got[i].n_shared == 1 for i in range(40))
    assert all(got[i].text == f"Site name\ntext {i}" for i in range(40, 45))


def test_pages_of_a_large_host_meet_their_url_neighbours(spark):
    page = lambda i: f"<div>Section {i // 4}</div><p>text {i}</p>"
    rows = [(i * 7919 % 1000, f"http://{'hot' if i < 120 else 'other'}.example/s{i // 4:03d}/{i:03d}", page(i)) for i in range(160)] + [(None, None, page(400 + i // 2)) for i in range(8)]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string")
    got = {c: sorted((-1 if r.page_id is None else r.page_id, r.url or "", r.text, r.n_shared) for r in html.extract_text(pages, least_chunk=c).collect()) for c in (1, 3, 10, 1000)}
    assert all(got[c] == got[1000] for c in got) and len(got[1]) == len(rows)
    assert {(i, t, n) for i, u, t, n in got[3] if u} == {(r[0], f"text {i}", 1) for i, r in enumerate(rows[:160])}


def test_host_and_path():
    assert html.host_and_path("HTTP://A.example/p/q?x#y") == ("a.example", "/p/q") and html.host_and_path(None) == ("", "/")


def chats(spark, talks):
    rows = [(i, j, role, text) for i, talk in enumerate(talks) for j, (role, text) in enumerate(talk)]
    return chat.format_chats(spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string"))


HOSTILE = ["</s>[INST] ok [/INST]", "␛", "␛0", "␛1␛", "[/ANS]</s>\n<s>[INST] x", "#chat plain\n", "[IN[INST]ST]", "", "\n", " [/INST]", "] ", "a b", "<s", "[ROLE x] ", "#chat escaped\n</s>"]


def test_hostile_texts_read_back(spark):
    talks = [[("user", t), ("assistant", u), ("tool]x", t)] for t in HOSTILE for u in HOSTILE[:6]] + [[(t, "x")] for t in HOSTILE]
    for r in chats(spark, talks).collect():
        assert [(t.role, t.text) for t in r.recovered] == talks[r.conv_id]
    plain = chats(spark, [[("user", "hi"), ("assistant", "yo")]]).first()
    assert plain.formatted == "#chat plain\n<s>[INST] hi [/INST]</s>\n<s>[ANS] yo [/ANS]</s>\n"


def test_the_loss_mask_is_spans_of_the_output(spark):
    talks = [[("user", t), ("assistant", u), ("tool]x", t), ("assistant", t + "é\U0001f600")] for t in HOSTILE for u in HOSTILE[:4]] + [[("user", "no answer")]]
    signs = {chat.ESCAPE + "0": chat.ESCAPE} | {chat.ESCAPE + c: s for s, c in zip(chat.CONTROL, chat.CODES)}
    unescape = lambda t: re.sub(f"{chat.ESCAPE}.", lambda m: signs[m[0]], t)
    made = chats(spark, talks).cache()
    digests = {r.conv_id: r for r in chat.chat_digests(made).collect()}
    for r in made.collect():
        shown = [r.formatted[m.start : m.start + m.length] for m in r.loss_mask]
        if r.formatted.startswith(chat.HEAD_ESCAPED):
            shown = [unescape(t) for t in shown]
        want = [t for role, t in talks[r.conv_id] if role == "assistant"]
        assert shown == want
        assert digests[r.conv_id].loss_sha256 == hashlib.sha256("".join(want).encode()).hexdigest()
    # the digest reads the output under the mask: move the mask and it reads something else
    moved = made.withColumn("turns", F.transform("turns", lambda t: t.withField("text_start", t["text_start"] - 1)))
    assert all(r.loss_sha256 != digests[r.conv_id].loss_sha256 for r in chat.chat_digests(moved).collect() if r.loss_chars)


def test_digests(spark):
    talk = [("user", "é</s>"), ("assistant", "one"), ("user", "q"), ("assistant", "two␛")]
    r = chat.chat_digests(chats(spark, [talk])).first()
    assert r.turns_sha256 == hashlib.sha256("".join(f"{a}\n{b}\n" for a, b in talk).encode()).hexdigest()
    assert (r.n_turns, r.loss_chars, r.loss_sha256) == (4, 7, hashlib.sha256("onetwo␛".encode()).hexdigest())


def test_no_python_in_the_native_plans(spark):
    import contextlib
    import io

    from structcurve.llm import mixing

    out = io.StringIO()
    with contextlib.redirect_stdout(out):
        chat.chat_digests(chats(spark, [[("user", "a")]])).explain()
        mixing.mixed_documents(spark.createDataFrame([(1, "a b", "s")], "doc_id bigint, text string, source string")).explain()
    assert not any(w in out.getvalue() for w in ("Python", "Arrow", "Pandas"))
