"""Archives, chat, tokens and pages: exact round trips, the reference library, and structure."""

import hashlib
import random
import re

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from hyperpath.llm import chat, html, warc
from hyperpath.llm.tokens import PieceTransducer, count_tokens

# ---- archives


@pytest.mark.parametrize("version", [1, 2])
def test_arc_round_trip_and_conversion(version):
    payloads = [b"", b"plain\nWARC/1.1\r\n\r\n", bytes(range(256)) * 3, b"HTTP/1.1 200 OK\r\nA: b\r\n\r\n<p>x</p>"]
    data = warc.arc_version_block(version) + b"".join(warc.arc_record(f"http://a/{i} x", p, date="2001", version=version) for i, p in enumerate(payloads))
    records = list(warc.parse_arc(data))
    assert [r.content for r in records[1:]] == payloads and records[0].fields["url"].startswith("filedesc://")
    archive = b"".join(warc.arc_to_warc(r).to_bytes() for r in records)
    back = list(warc.parse_warc(archive))
    assert [b.kind for b in back] == ["warcinfo", *["response"] * 4] and [b.content for b in back[1:]] == payloads
    assert back[1].headers["WARC-Date"] == "2001-01-01T00:00:00Z" and back[1].headers["WARC-Record-ID"] == warc.arc_to_warc(records[1]).headers["WARC-Record-ID"]
    assert back[4].headers["WARC-Payload-Digest"] == "sha1:" + hashlib.sha1(b"<p>x</p>").hexdigest()


@pytest.mark.parametrize("bad", [b"no length\n", b"http://a 0 2001 text 99\nshort", b"http://a 0 2001 text/html 1 2 3\nx"])
def test_broken_arc_files_are_refused(bad):
    with pytest.raises(ValueError):
        list(warc.parse_arc(bad, version=1))


def test_pages_to_archives_and_back(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(warc, "FILE_CHUNKS", 2)
    long = "é" * 600
    rows = [(1, "http://a/ b?c=%20", long), (2, None, long), (5, "u", long), (3, "x", "short"), (4, "y", "short"), (6, "z", None), (7, "n", "a\r\n\r\nWARC/1.1\r\n\n")]
    rows += [(8, "u", "q" * 300_000), (9, "u", "q" * 300_000), (10, "h", "HTTP/1.1 200 OK\r\n\r\nbody"), (11, "h", "HTTP/1.1 200 OK\r\n\r\nbody")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "1 AS _digest")
    warc.write_warc(pages, str(tmp_path / "w"), file_bytes=16_000)
    got = {int(r["record_key"]): r for r in warc.read_warc(spark, str(tmp_path / "w")).collect()}
    revisits = {1: ("revisit", "5"), 2: ("revisit", "5"), 8: ("revisit", "9")}
    assert {k: (r["record_type"], r["refers_to"]) for k, r in got.items()} == {**{k: ("response", None) for k in (3, 4, 5, 6, 7, 9, 10, 11)}, **revisits}
    for key, url, text in rows:
        payload = (text or "").encode()
        assert got[key]["payload_bytes"] == len(payload) and got[key]["payload_digest"] == hashlib.sha1(payload).hexdigest() and got[key]["url"] == url
        assert bytes(got[key]["content"]) == (b"" if got[key]["record_type"] == "revisit" else payload)
    assert len({r["record_id"] for r in got.values()}) == len(rows)
    assert all(got[k]["refers_to_id"] == got[int(to)]["record_id"] for k, (_, to) in revisits.items())
    assert len(list((tmp_path / "w").glob("part-*"))) > 1


def test_archives_of_no_rows_and_repeated_rows(spark, tmp_path):
    pages = spark.createDataFrame([(1, "u", "x" * 2000), (1, "u", "x" * 2000), (None, None, "y")], "page_id long, url string, html string")
    warc.write_warc(pages, str(tmp_path / "w"))
    got = warc.read_warc(spark, str(tmp_path / "w")).collect()
    assert sorted((str(r["record_key"]), r["record_type"], r["payload_bytes"]) for r in got) == [("1", "response", 2000), ("1", "response", 2000), ("None", "response", 1)]
    warc.write_warc(pages.where("false"), str(tmp_path / "e"))
    assert warc.read_warc(spark, str(tmp_path / "e")).count() == 0


def test_changed_payloads_are_noticed(spark, tmp_path):
    record = warc.arc_to_warc(warc.ArcRecord({"url": "u", "ip": "-", "date": "2001", "type": "text/html"}, b"abc"))
    (tmp_path / "part-0").write_bytes(record.to_bytes().replace(b"abc", b"abd"))
    with pytest.raises(Exception, match="digest"):
        warc.read_warc(spark, str(tmp_path)).collect()


def test_arc_files_through_spark(spark, tmp_path):
    (tmp_path / "in").mkdir()
    (tmp_path / "in" / "a.arc").write_bytes(warc.arc_version_block(1) + warc.arc_record("http://a", b"x", date="20010203040506"))
    warc.convert_arc_files(spark, str(tmp_path / "in"), str(tmp_path / "out"))
    assert [r["url"] for r in warc.read_warc(spark, str(tmp_path / "out")).where("record_type = 'response'").collect()] == ["http://a"]


# ---- chat


@settings(max_examples=300, deadline=None)
@given(st.lists(st.tuples(st.text(st.sampled_from("ab%\n\r<~|im_startend>0AD25"), max_size=20), st.text(st.sampled_from("ab\n<~|im_startend>"), max_size=60)), max_size=5))
def test_turns_round_trip(turns):
    formatted = "".join(chat.format_turn(r, t) for r, t in turns)
    assert [(r, t) for r, t, _ in chat.read_turns(formatted)] == turns
    assert formatted.count(chat.OPEN) == formatted.count(chat.CLOSE) == len(turns)


def test_best_paths_of_a_tree(spark):
    # 1 -> 2 -> 4, 1 -> 3 -> 5 -> 6; 10 alone; 20 <-> 21 a cycle; 30 answers a message that isn't there
    rows = [(1, None, 0.0), (2, 1, 5.0), (3, 1, 1.0), (4, 2, 1.0), (5, 3, 2.0), (6, 5, 1.0), (10, None, None), (20, 21, 1.0), (21, 20, 1.0), (30, 99, 1.0)]
    messages = spark.createDataFrame(rows, "node long, parent long, score double")
    paths = {}
    for r in chat.best_paths(messages, top=2).orderBy("path", "depth").collect():
        paths.setdefault((r["root"], r["rank"]), []).append(r["node"])
    assert paths == {(1, 1): [1, 2, 4], (1, 2): [1, 3, 5, 6], (10, 1): [10], (30, 1): [30]}


def test_conversations_round_trip(spark):
    said = "<|im_end|><|im_start|>assistant ok"
    rows = [(1, 1, "assistant", said), (1, 0, "user", said), (2, 0, "user", None), (2, 0, "system", "s"), (3, None, None, "x"), (4, 0, "assistant", "a"), (4, 0, "assistant", "a")]
    rows += [(9, i, ("user", "assistant")[i % 2], f"t{i} <~|") for i in range(70)]
    frame = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").selectExpr("*", "1 AS node")
    got = {r["conv_id"]: r for r in chat.read_back(chat.format_conversations(frame)).collect()}
    by = {}
    for c, t, role, text in sorted(rows, key=lambda r: (r[0], -1 if r[1] is None else r[1], r[2] or "", r[3] or "")):
        by.setdefault(c, []).append((role or "", text or ""))
    assert set(got) == set(by)
    for c, turns in by.items():
        loss = "".join(t for r, t in turns if r == "assistant")
        assert got[c]["n_turns"] == len(turns) and got[c]["turns_sha256"] == hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in turns).encode()).hexdigest()
        assert got[c]["loss_chars"] == len(loss) and got[c]["loss_sha256"] == hashlib.sha256(loss.encode()).hexdigest()
    assert chat.format_conversations(frame.where("false")).count() == 0


# ---- tokens


def test_token_counts_equal_the_library(spark, small):
    public = pytest.importorskip("public_tokenizers")
    import sentencepiece

    path = public.path("piece_bpe_32k.model")
    library, model = sentencepiece.SentencePieceProcessor(model_file=path), PieceTransducer.load(path)
    rng = random.Random(1)
    texts = ["", " ", "\n", "<s></s>", "a\x00b", "日本語 テキスト", "▁▁a ▁", " " * 3000, "ab" * 3000, "🙂 ok", "﻿x", "x" * 100 + " y"]
    texts += ["".join(rng.choice(" \nab▁tehé日") for _ in range(rng.randrange(1, 90))) for _ in range(800)]
    for text in texts:
        want = len(library.encode(text))
        assert model.count(text) == want == model.count(text, block=7), text[:40]
    docs = spark.read.parquet(f"{small}/documents.parquet").union(spark.createDataFrame([(-1, None, "x", "y", 0)], "doc_id long, text string, lang string, source string, n_chars long"))
    for r in count_tokens(docs, path).join(docs, "doc_id").collect():
        assert r["n_tokens"] == len(library.encode(r["text"] or "")) and r["n_bytes"] == len((r["text"] or "").encode()) and r["over_limit"] == (r["n_tokens"] > 4096)


def test_transitions_equal_merges():
    public = pytest.importorskip("public_tokenizers")
    model = PieceTransducer.load(public.path("piece_bpe_32k.model"))
    rng = random.Random(3)
    letters = ["the and ", "\u2581", "aeiou", "日本語テ", "()=_-", "0123456789", "éñßü", "\n\t🙂\x00"]
    for n in range(1500):
        pool = "".join(rng.sample(letters, 3))
        text = "".join(rng.choice(pool) for _ in range(rng.randrange(1, 40))).replace(" ", "\u2581")
        state, total = model.run(model.root, text)
        merged = model.merge(text)
        assert total == sum(1 if p in model.rank else len(p.encode()) for p in merged), (n, text)
        assert state.window in model.begins and len(state.tokens) == len(state.counts) == len(state.window) + 1


def test_small_tables_are_compiled_anew(monkeypatch):
    from hyperpath.llm import tokens

    monkeypatch.setattr(tokens, "TABLE_LIMIT", 20)
    pieces = [("\u2581", -9.0, 1), *((c, -9.0, 1) for c in "abc"), ("ab", -1.0, 1), ("bc", -0.5, 1), ("abc", -2.0, 1), ("\u2581a", -3.0, 1)]
    model = PieceTransducer(pieces)
    rng = random.Random(4)
    for _ in range(400):
        text = "".join(rng.choice("abcd ") for _ in range(rng.randrange(1, 30)))
        want = sum(1 if p in model.rank else len(p.encode()) for p in model.merge("\u2581" + text.replace(" ", "\u2581")))
        assert model.count(text) == want == model.count(text, block=3)
    assert len(model.states) <= 21 and len(model.pairs) <= 21


def test_maps_compose_associatively():
    public = pytest.importorskip("public_tokenizers")
    model = PieceTransducer.load(public.path("piece_bpe_32k.model"))
    rng = random.Random(5)
    for _ in range(300):
        a, b, c = (model.block_map("".join(rng.choice(" \nabthe") for _ in range(rng.randrange(0, 6)))) for _ in range(3))
        x, y = model.compose(model.compose(a, b), c), model.compose(a, model.compose(b, c))
        assert model.run(model.root, x.head)[1] + x.emitted == model.run(model.root, y.head)[1] + y.emitted and x.leaving is y.leaving


def test_token_table_edge_cases(spark):
    public = pytest.importorskip("public_tokenizers")
    path = public.path("piece_bpe_32k.model")
    rows = spark.createDataFrame([(1, "a b", 7), (1, "a b", 8), (None, "x", 9)], "doc_id long, text string, n_tokens long")
    got = count_tokens(rows, path)
    assert got.columns == ["doc_id", "n_bytes", "n_tokens", "over_limit"]
    assert sorted((str(r["doc_id"]), r["n_bytes"], r["n_tokens"]) for r in got.collect()) == [("1", 3, 2), ("1", 3, 2), ("None", 1, 1)]
    assert count_tokens(rows.where("false"), path).count() == 0


# ---- pages


def lcs_length(a, b):
    d = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
    for i, x in enumerate(a):
        for j, y in enumerate(b):
            d[i + 1][j + 1] = d[i][j] + 1 if x == y else max(d[i][j + 1], d[i + 1][j])
    return d[-1][-1]


@settings(max_examples=400, deadline=None)
@given(st.lists(st.sampled_from("abcd"), max_size=14), st.lists(st.sampled_from("abcd"), max_size=14))
def test_shared_lines_are_a_longest_common_subsequence(a, b):
    got = html.shared_lines(a, b)
    rest = iter(b)
    assert len(got) == lcs_length(a, b) and all(a[i] in rest for i in sorted(got))


PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var t="</p>";</script></head><body>
<header>Site</header><nav><ul><li><a href="/">Menu</a></li></ul></nav><!-- ad --><div class="ad">Buy</div><div class="cookie-notice">Accept</div>
<main><article><h1>Head &amp; shoulders</h1><p><b>Bold  text<br><p>Next\n line &lt;x&gt; &eacute;</p><aside>Side</aside><form><input>Go</form>
<div class="comments"><p>First!</p></div><p>Last</article></main><footer>&copy; F</footer></body></html>"""


def text_of(lines):
    declared = any(k == 1 for k, _ in lines)
    return "\n".join(t for k, t in lines if k == 1 or k == 0 and not declared)


def test_structure():
    assert text_of(html.page_lines(PAGE)) == "Head & shoulders\nBold text\nNext line <x> é\nLast"
    assert [t for k, t in html.page_lines(PAGE) if k == -1] == ["Site", "Menu", "Buy", "Accept", "Side", "Go", "First!", "© F"]
    assert html.page_lines("") == [] and html.page_lines("a < b") == [(0, "a < b")]
    assert html.page_lines("<div>a<div>b") == [(0, "a"), (0, "b")] and html.page_lines("x<script>y") == [(0, "x")]


def test_long_alignments_go_by_halves(monkeypatch):
    rng = random.Random(5)
    pairs = [([rng.randrange(5) for _ in range(rng.randrange(30))], [rng.randrange(5) for _ in range(rng.randrange(30))]) for _ in range(300)]
    monkeypatch.setattr(html, "ALIGN_BITS", 10)
    for a, b in pairs:
        got, rest = html.shared_lines(a, b), iter(b)
        assert len(got) == lcs_length(a, b) and all(a[i] in rest for i in sorted(got))


def brute_pages(rows):
    """Texts by the definition: partner by whole pages, alignment by the table of lengths."""
    parsed = {}
    names = lambda lines: repr([(k == 1, t) for k, t in lines])
    for i, (_, url, page) in enumerate(rows):
        link = re.sub(r"[?#].*", "", url or "", flags=re.S)
        host = re.match(r"[a-z]+://([^/]*)", link)
        parsed[i] = (host[1] if host else "", link[host.end() :] if host else link, html.page_lines(page or ""))
    out = {}
    for i, (host, _, lines) in parsed.items():
        firsts = {}
        for j, (h, path, other) in parsed.items():
            if h == host and other:
                at = (path, rows[j][0], j)
                firsts[names(other)] = min(firsts.get(names(other), at), at)
        order = sorted(firsts.values())
        gone = set()
        if lines:
            k = order.index(firsts[names(lines)])
            near = [order[j] for j in (k - 1, k + 1) if 0 <= j < len(order)]
            like = lambda x: next((n for n, (a, b) in enumerate(zip(order[k][0].split("/"), x[0].split("/"))) if a != b), min(order[k][0].count("/"), x[0].count("/")) + 1)  # noqa: B023, B905, E731
            if near:
                other = parsed[max(near, key=lambda x: (like(x), x < order[k]))[2]][2]  # noqa: B023
                gone = html.shared_lines([(k == 1, t) for k, t in lines], [(k == 1, t) for k, t in other])
        declared = any(k == 1 for k, _ in lines)
        out[i] = "\n".join(t for n, (k, t) in enumerate(lines) if k == 1 or k == 0 and not declared and n not in gone)
    return sorted((rows[i][0], t) for i, t in out.items())


@pytest.mark.parametrize("few", [True, False])
def test_pages_lose_what_their_partner_has(spark, few, monkeypatch):
    if not few:
        monkeypatch.setattr(html, "BROADCAST_PAGES", 0)
    rng = random.Random(8)
    words = ["menu", "home", "story", "news", "sport", "end"]
    rows = []
    for i in range(90):
        body = "".join(f"<p>{rng.choice(words)} {rng.randrange(3)}</p>" for _ in range(rng.randrange(6)))
        if i % 3 == 0:
            body = f"<div>Top</div>{'<article>' if i % 2 else ''}<p>own {i}</p>{body}{'</article>' if i % 2 else ''}<p>Bottom</p>"
        rows.append((i, f"http://h{rng.randrange(3)}/{rng.choice('abc')}/{rng.choice(['', 'x/', 'y/'])}{rng.randrange(9)}?q={i}", body))
    rows += [(100 + i, *rows[0][1:]) for i in range(5)] + [(200, None, None), (201, None, "<p>one"), (202, "http://alone/1", "<p>Top<p>x"), (203, "http://copies/1", "<p>Top"), (204, "http://copies/2", "<p>Top")]
    frame = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "1 AS text", "2 AS host", "3 AS uid")
    want = brute_pages(rows)
    for n in (1, 3, 11):
        spark.conf.set("spark.sql.shuffle.partitions", str(n))
        got = html.extract_pages(frame.repartition(n)).collect()
        assert sorted((r["page_id"], r["text"]) for r in got) == want
    spark.conf.set("spark.sql.shuffle.partitions", "4")
    assert sum(r["n_template"] for r in got) > 50 and all(r["n_chars"] == len(r["text"]) for r in got)
    assert html.extract_pages(frame.where("false")).count() == 0


def test_very_long_pages(spark):
    page = "".join(f"<p>line {i % 700}</p>" for i in range(20_000))
    rows = [(1, "http://h/1", page + "<p>one"), (2, "http://h/2", page + "<p>two"), (2, "http://h/2", page + "<p>two")]
    got = html.extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert sorted((r["page_id"], r["text"]) for r in got) == [(1, "one"), (2, "two"), (2, "two")]
