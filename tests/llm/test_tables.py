"""URL filters and preference formatting against plain Python, and the registered queries with SQL."""

import collections

import duckdb
import pytest

from rdf_assist.llm import chat, queries, urls

RULES = [*queries.URL_RULES, ("block", "org", "/a"), ("allow", "org", "/a/b"), ("block", "a.b.example.org", "/"), ("block", "org", "/a/b"), ("allow", "EXAMPLE.org", "/a/bc")]
URLS = [None, "", "no scheme", "http://org/a/b/c", "https://x.example.org/es/1", "http://EXAMPLE.ORG/en/1?q", "http://example.org", "http://a.b.example.org/x#y", "http://q.a.b.example.org/a/bcd", "ftp://com/fr/", "http://notorg/a", "x://com/de/?a/b", "http://example.org/a/bc", "http://.../", "http://org.example.org/a/b"]


def _plain(url):
    if url is None or "://" not in url:
        return "", "", None, "allow"
    rest = url.split("://", 1)[1]
    cut = min([rest.find(c) for c in "/?#" if c in rest], default=len(rest))
    host, tail = rest[:cut].lower(), rest[cut:]
    path = tail[: min([tail.find(c) for c in "?#" if c in tail], default=len(tail))]
    fits = [(len(h + p), len(h), v, h.lower() + p) for v, h, p in RULES if (host == h.lower() or host.endswith("." + h.lower())) and path.startswith(p)]
    best = max(fits, default=None)
    return host, path, best and best[3], best[2] if best else "allow"


@pytest.mark.parametrize("salts", [1, 5])
def test_url_rules(spark, salts):
    pages = spark.createDataFrame([(i % 9, u, "h", 1) for i, u in enumerate(URLS * 2)], "page_id int, url string, html string, salt int")
    got = collections.Counter((r.page_id, r.host, r.path, r.rule, r.verdict) for r in urls.judge(pages, urls.rule_frame(spark, RULES), salts=salts).collect())
    assert got == collections.Counter((i % 9, *_plain(u)) for i, u in enumerate(URLS * 2))


def test_url_empty(spark):
    pages = spark.createDataFrame([(1, "http://a.org/")], "page_id int, url string")
    assert urls.judge(pages.limit(0), urls.rule_frame(spark, RULES)).count() == 0
    assert urls.judge(pages, urls.rule_frame(spark, RULES).limit(0)).first().verdict == "allow"


def test_preference_format(spark):
    rows = [
        (1, [("user", "hi"), ("assistant", "yes")], [("user", "hi"), ("assistant", "no")]),
        (2, [("user", "a")], [("user", "a")]),
        (3, None, [("assistant", "<|end|>")]),
        (4, [("user", None)], []),
        (5, [("user", "a"), ("assistant", "b")], [("user", "a"), ("assistant", "b"), ("user", "c"), ("assistant", "d")]),
    ]
    frame = spark.createDataFrame(rows, "k int, chosen array<struct<role:string,text:string>>, rejected array<struct<role:string,text:string>>")
    got = {r.k: r for r in chat.format_pairs(frame).collect()}
    assert [got[k].n_common for k in range(1, 6)] == [1, 1, 0, 0, 2]
    assert got[1].prompt == "<|user|>\nhi<|end|>\n" and got[1].chosen_text == "<|assistant|>\nyes<|end|>\n"
    for r in got.values():
        for side in ("chosen", "rejected"):
            text, spans = r[f"{side}_text"], r[f"{side}_mask"]
            assert "".join(text[s["from"] : s["to"]] for s in spans) == "".join(x.split("|>\n", 1)[1] + "<|end|>\n" for x in text.split("<|end|>\n") if x.startswith("<|assistant"))
    assert "< |end|>" in got[3].rejected_text
    assert got[5].chosen_text == "" and got[5].rejected_mask[0]["from"] > 0


def test_turn_ties_and_nulls(spark):
    rows = [(1, 0, "user", "b"), (1, 0, "user", "a"), (None, 0, "user", "x"), (0, None, None, None), (0, 1, "assistant", "r")]
    frame = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = {r.conv_id: [t.text for t in r.turns] for r in chat.conversations(frame).collect()}
    assert got == {1: ["a", "b"], 0: ["", "r"]}
    assert chat.reply_pairs(frame).count() == 0
    assert chat.conversations(frame.limit(0)).count() == 0


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_sql(spark, tiny, name):
    con = duckdb.connect()
    for t in ("pages", "conversations", "documents"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{tiny}/{t}.parquet'")
    df = queries.queries()[name](spark, tiny)
    columns = sorted(df.columns)
    want = con.sql(f"SELECT {', '.join(columns)} FROM ({queries.oracle_sql()[name]})").fetchall()
    assert collections.Counter(tuple(r) for r in df.select(columns).collect()) == collections.Counter(want)
