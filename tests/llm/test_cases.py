"""Empty tables, nulls, repeated rows, clashing names and long texts for every operator; and the parts of operators that larger data reach."""

import hashlib
import zlib
from fractions import Fraction

import numpy as np
import pytest

from planepack.llm import chat, decontam, jaccard, pieces, secrets, shards, topk, toxicity, urls, warc

DOCS = "doc_id long, text string, source string, __id string, __s string, __fp string, node string, __u string, __b string"
ROWS = [(1, "one two three four"), (1, "one two three four"), (None, "alpha beta gamma delta"), (2, None), (3, ""), (4, "漢字" * 2000 + "x" * 30_000), (None, "alpha beta gamma delta")]


def docs(spark, rows=ROWS):
    return spark.createDataFrame([(i, t, None if n % 3 == 0 else f"s{n % 2}", *"abcdef") for n, (i, t) in enumerate(rows)], DOCS)


def bench(spark, rows):
    return spark.createDataFrame(rows, "item_id long, text string, doc_id string, __n string")


OPERATORS = {
    "pieces": lambda s, d: pieces.encode(d),
    "jaccard": lambda s, d: jaccard.jaccard_components(d, links=True),
    "decontam": lambda s, d: decontam.hits(d, bench(s, [(1, "two three", "x", "y")])),
    "secrets": lambda s, d: secrets.scan_secrets(d),
    "toxicity": lambda s, d: toxicity.score(d, toxicity.fit_chain(d, s.createDataFrame([(1, 1, 0)], "doc_id long, quality int, toxic int"))),
    "shards": lambda s, d: shards.shard(d, buckets=4).select("doc_id", "size", "text_crc32"),
}


@pytest.mark.parametrize("name", OPERATORS)
def test_documents(spark, name):
    """One row a row: rows that are equal get equal results, null ids stay, and nothing comes of nothing."""
    df = docs(spark)
    got = OPERATORS[name](spark, df).collect()
    assert sorted((r.doc_id for r in got), key=str) == sorted((i for i, _ in ROWS), key=str)
    for key in (1, None):
        assert len({str(r) for r in got if r.doc_id == key}) == 1
    assert OPERATORS[name](spark, df.limit(0)).collect() == []


def test_links_count_rows_without_ids(spark):
    got = {(r.doc_id, r.n_shingles): (r.n_class, r.n_links) for r in jaccard.jaccard_components(docs(spark), links=True).collect()}
    assert got[(1, 2)] == (2, 1) and got[(None, 2)] == (2, 1) and got[(2, 0)] == (1, 0) and got[(4, 1)] == (1, 0)


def test_pages(spark):
    ddl = "page_id long, url string, html string, __id string, host string, key string, block string"
    rows = [(1, "http://a.org/x", "<p>"), (1, "http://a.org/x", "<p>"), (None, None, None), (2, "no url", ""), (3, "http://a.org/x", "y" * 200_000)]
    df = spark.createDataFrame([(*r, *"abcd") for r in rows], ddl)
    assert len(urls.judge(df).collect()) == 5 and urls.judge(df.limit(0)).collect() == []
    path = warc.fresh(spark, "test")
    warc.write_archives(df, f"{path}/a", records_per_file=2)
    warc.build_index(spark, f"{path}/a", f"{path}/i", per_block=1)
    for parts in (warc.DIRECTORY_ROWS, 2):  # the directory whole, and in parts
        got = sorted(((r.page_id, r.payload_bytes, r.record_type) for r in warc.read_pages(warc.lookup(spark, f"{path}/i", df.select("url"), parts)).collect()), key=str)
        assert got == sorted([(1, 3, "response"), (1, 3, "response"), (None, 0, "revisit"), (2, 0, "response"), (3, 200_000, "response")], key=str)
    assert warc.lookup(spark, f"{path}/i", spark.createDataFrame([("http://b.org/",)], "url string")).collect() == []
    index = warc.CaptureIndex(spark, f"{path}/i")
    assert len(index.lookup("http://a.org/x")) == 3
    warc.write_archives(df.limit(0), f"{path}/none")
    assert [r for r in warc.parse_records(b"")] == []


def test_streamed_records_equal_parsed_ones(tmp_path):
    block = lambda body: b"HTTP/1.1 200 OK\r\nContent-Length: %d\r\n\r\n" % len(body) + body
    data = b"".join(b"WARC/1.1\r\nWARC-Type: response\r\nContent-Length: %d\r\n\r\n" % len(block(x)) + block(x) + b"\r\n\r\n" for x in (b"", b"abc", b"z" * 5000, b"\r\n\r\nWARC/1.1\r\n"))
    (tmp_path / "f").write_bytes(data)
    for chunk in (1, 7, 100, 1 << 20):
        with open(tmp_path / "f", "rb") as f:
            assert list(warc.stream_records(f, chunk)) == list(warc.parse_records(data))
    (tmp_path / "g").write_bytes(data[:-3])
    with pytest.raises(ValueError, match="ends inside"), open(tmp_path / "g", "rb") as f:
        list(warc.stream_records(f, 50))


def test_topk_in_blocks(spark):
    rng = np.random.default_rng(4)
    rows = [(i, [float(v) for v in rng.integers(-9, 9, 4)]) for i in range(300)] + [(100, [0.5] * 4), (7, [1.0, 2.0]), (200, [3.0, 1.0])]
    df = spark.createDataFrame([(*r, "x", "y") for r in rows], "vec_id long, embedding array<double>, query_id string, score string")
    want = []
    for q in (0, 100, 200):
        mine = min(v for i, v in rows if i == q)
        s = sorted((-sum(int(np.floor(1024 * a)) * int(np.floor(1024 * b)) for a, b in zip(mine, v, strict=True)), i) for i, v in rows if i != q and len(v) == len(mine))[:10]
        want += [(q, n + 1, i, -x) for n, (x, i) in enumerate(s)]
    for size in (topk.BLOCK_BYTES, 40):  # all queries at once, and one or two at a time
        got = sorted(map(tuple, topk.exact_topk(df, block_bytes=size).select("query_id", "rank", "vec_id", "score").collect()))
        assert got == want
    assert topk.exact_topk(df.limit(0)).collect() == []


def test_benchmark_in_parts(spark):
    rng = np.random.default_rng(6)
    word = lambda: f"w{rng.integers(15)}"
    items = [(i, " ".join(word() for _ in range(k)), "x", "y") for i, k in enumerate([2, 5, 12, 25, 25, 11, 10, 3, 40])]
    rows = [(i, " ".join(word() for _ in range(60))) for i in range(20)] + [(50, items[3][1]), (51, None)]
    df, b = docs(spark, rows), bench(spark, items)
    one, many = (sorted(map(tuple, decontam.hits(df, b, part_chars=k).collect())) for k in (10**6, 60))
    assert one == many
    one, many = (sorted((tuple(r) for r in decontam.remove_spans(df, b, part_chars=k).collect()), key=str) for k in (10**6, 60))
    assert one == many


def test_shards_against_plain_python(spark):
    rows = [(i, f"text {i % 17}") for i in range(200)] + [(None, None), (None, ""), (5, "text 5")]
    df = docs(spark, rows)
    held = [(r.doc_id, r.source, r.text or "") for r in df.collect()]
    draw = lambda *x: int(hashlib.md5(":".join(x).encode()).hexdigest()[:15], 16)
    key = {}
    for i, s, t in held:
        crc = zlib.crc32(t.encode())
        key.setdefault("" if s is None else f"s{s}", []).append((draw("17", "none" if i is None else str(i), str(crc)), i, crc, len(t.encode()) + 8))
    order = []
    for s, mine in key.items():
        mine.sort(key=lambda x: ((x[0] >> 20) % 8, x[0], x[1] is not None, x[1] or 0, x[2], x[3]))
        order += [(Fraction(2 * r + 1, 2 * len(mine)), hashlib.md5(f"17:{s}".encode()).hexdigest(), s, x) for r, x in enumerate(mine)]
    order.sort(key=lambda o: (float(o[0]), o[1], o[2], o[3][0], o[3][1] is not None, o[3][1] or 0, o[3][2]))
    n, want = len(order), []
    for pos, (_, _, _, (_, i, crc, size)) in enumerate(order):
        shard = pos * 7 // n
        want.append((i, size, crc, shard, pos - (shard * n + 6) // 7))
    got = [(r.doc_id, r.size, r.text_crc32, r.shard, r.slot) for r in shards.shard(df, shards=7, buckets=8).collect()]
    assert sorted(got, key=str) == sorted(want, key=str)
    assert "Python" not in shards.shard(df, buckets=8)._jdf.queryExecution().toString()


def test_long_runs_without_spaces_are_cut_where_no_piece_reaches(spark):
    lat = pieces.Lattices()
    for unit in (" 漢字仮名" * 1, " " + "漢字仮名交じり文" * 200, " " + "abcdefgh" * 300, " é" + "日本語x" * 100):
        parts = lat.split(unit)
        assert "".join(parts) == unit
        ends = set(np.cumsum([len(x) for x in parts]).tolist())
        for s in range(len(unit)):
            for d in range(2, min(lat.longest, len(unit) - s) + 1):
                if unit[s : s + d] in lat.pieces:
                    assert not any(s < c < s + d for c in ends)
    texts = ["漢字仮名交じり文" * 5000, "", None]
    got = sorted(pieces.encode(docs(spark, list(enumerate(texts))), decoded=True).collect())
    assert [r.decoded for r in got] == texts


def test_marks_in_rules_are_literal(spark):
    rules = (("block", "a.org", "/x*y"), ("allow", "a.org", "/"))
    pages = spark.createDataFrame([(1, "http://a.org/x*y/1"), (2, "http://a.org/xzy/1"), (3, "http://a.org/x?y")], "page_id long, url string")
    assert {r.page_id: r.verdict for r in urls.judge(pages, rules=rules, globs=()).collect()} == {1: "block", 2: "allow", 3: "allow"}


def test_template_trimming_and_errors():
    assert chat.render("a  {%- if 3 not in x -%}  b  {%- endif -%}  c", x=[1]) == "abc"
    assert chat.render("{{ 1 in x }}{{ 1 not in x }}{{ not 1 in x }}", x=[1]) == "TrueFalseFalse"
    assert chat.render("x {#- gone -#} y") == "xy"
    for bad in ("{{ 'a' + 1 }}", "{{ 1 < 'b' }}", "{{ 3 | length }}", "{{ 1 in 2 }}"):
        with pytest.raises(chat.TemplateError):
            chat.render(bad)
    with pytest.raises(chat.TemplateError):
        chat.render("{{ x - y }}", x="a", y=None)
    assert chat.render("{{ 5 | upper }}{{ none | escape }}") == "5"


def test_formatted_conversations_hold_their_masks(spark):
    df = spark.createDataFrame([(1, 1, "assistant", "b[c"), (1, 0, "user", "a"), (2, 0, None, None), (2, 0, None, None)], "conv_id long, turn long, role string, text string")
    got = {r.conv_id: r for r in chat.format_conversations(df).collect()}
    assert [chat.unescape(got[1].formatted[a:b]) for a, b in got[1].mask] == ["b[c"] and got[2].mask == []
    assert chat.read_back(got[1].formatted) == [("user", "a"), ("assistant", "b[c")] and len(chat.read_back(got[2].formatted)) == 2
    assert chat.format_conversations(df.limit(0)).collect() == [] and chat.digest_conversations(df.limit(0)).collect() == []


def test_decoding_of_stored_ids(spark):
    texts = ["some text é", "", None]
    enc = pieces.encode(docs(spark, list(enumerate(texts))))
    assert sorted(map(tuple, pieces.decode_ids(enc).collect())) == list(enumerate(texts))


def test_fit_bounds(spark):
    rows = [(i, f"word{i} " * 50) for i in range(60)] + [(0, "again")] * 5
    labels = spark.createDataFrame([(i, 1, i % 2) for i in range(60)], "doc_id long, quality int, toxic int")
    small = toxicity.fit_chain(docs(spark, rows), labels, chars=0)
    assert small.weights == {} and toxicity.score(docs(spark, rows), small).filter("rejected").count() == 0
    assert len(toxicity.fit_chain(docs(spark, rows), labels).bias) == 2
