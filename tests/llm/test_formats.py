import random
import zlib

import duckdb
import numpy as np
import pyarrow.orc as orc
import pytest
from tokenizers import Tokenizer

from pathloom.llm import line_dedup, preference, token_output, url_filter
from pathloom.llm.queries import tokenizer_path

from .cases import docs

TURN = "conv_id long, turn long, role string, text string, pair_id long"


def turns(spark, rows):
    return spark.createDataFrame([(*r, 9) for r in rows], TURN)


def test_preferences(spark):
    rows = [(2, 0, "user", "hi"), (2, 1, "assistant", "yes"), (2, 2, "user", "more"), (2, 3, "assistant", "good"), (2, 4, "user", "bye"), (3, 0, "user", "q"), (3, 1, "assistant", "bad é"), (4, 0, "user", "alone"), (None, 0, "user", "x"), (5, 0, "assistant", None), (8, 0, None, None), (8, 1, "assistant", "s"), (9, 0, "assistant", "s")]
    got = {r["pair_id"]: r for r in preference.format_preferences(preference.preference_pairs(turns(spark, rows))).collect()}
    assert sorted(got) == [2, 3, 8, 9]
    a = got[2]
    assert a["n_prompt_turns"] == 3 and a["prompt"] == "<|user|>\nhi<|end|>\n<|assistant|>\nyes<|end|>\n<|user|>\nmore<|end|>\n"
    assert a["chosen"] == "<|assistant|>\ngood<|end|>\n" and a["rejected"] == "<|assistant|>\nbad é<|end|>\n"
    for side in ("chosen", "rejected"):
        assert [a[side][m["begin"] : m["end"]] for m in a[f"{side}_mask"]] == [a[side].removeprefix("<|assistant|>\n")]
    assert got[8]["n_prompt_turns"] == 2 and got[8]["chosen"] == got[8]["rejected"] == "" and got[8]["chosen_mask"] == [] and got[8]["prompt"].startswith("<||>\n<|end|>\n")


def test_prefix_of_any_two_conversations(spark):
    from pyspark.sql import functions as F

    t = "array<struct<role:string,text:string>>"
    u, a, b = ("user", "1"), ("assistant", "2"), ("assistant", "3")
    rows = [(1, [u, a, u], [u, b, u, a]), (2, [u], [u, a]), (3, [], [u]), (4, [u, a], [u, a]), (5, [a], [b])]
    df = spark.createDataFrame(rows, f"pair_id long, chosen {t}, rejected {t}")
    assert {r[0]: r[1] for r in df.select("pair_id", preference.common_prefix(F.col("chosen"), F.col("rejected"))).collect()} == {1: 1, 2: 1, 3: 0, 4: 2, 5: 0}
    r = preference.format_preferences(df).filter("pair_id = 1").first()
    assert [r["rejected"][m["begin"] : m["end"]] for m in r["rejected_mask"]] == ["3<|end|>\n", "2<|end|>\n"]
    assert preference.format_preferences(df.limit(0)).count() == 0


def test_lines(spark):
    html = lambda *x: "<html><nav>Menu</nav><p>" + "<br>".join(x) + "</p><script>var a='<p>Menu</p>'</script><!-- Menu --></html>"
    rows = [(i, f"http://A.example/{i}", html("shared" if i < 2 else "other", f"own {i}", "own too")) for i in range(10)] + [(20, "http://b.example/", html("few")), (None, "x", None), (21, None, ""), (22, "http://A.example/", None)]
    df = spark.createDataFrame([(*r, "h") for r in rows], "page_id long, url string, html string, host string")
    got = {r["page_id"]: r for r in line_dedup.drop_boilerplate(df).collect()}
    assert len(got) == len(rows)
    assert got[0]["text"] == "shared\nown 0" and got[5]["text"] == "own 5" and got[5]["n_lines"] == 4 and got[5]["n_dropped"] == 3
    assert got[20]["text"] == "Menu\nfew" and got[None]["n_lines"] == 0 and got[21]["text"] == "" and got[22]["host"] == "a.example"
    assert line_dedup.drop_boilerplate(df.limit(0)).count() == 0


def test_lines_of_small_hosts(spark):
    rows = [(10 * n + i, f"http://h{n}.example/{i}", f"<p>all</p><p>{'two' if i < 2 else 'rest'}</p><p>own {n} {i}</p>") for n in range(1, 8) for i in range(n)]
    pages = {r["page_id"]: r for r in line_dedup.drop_boilerplate(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    for n in range(1, 8):
        for i in range(n):
            line, on = ("two", min(n, 2)) if i < 2 else ("rest", n - 2)
            want = [x for x, k in (("all", n), (line, on), (f"own {n} {i}", 1)) if not (k > 1 and k > 0.3 * n)]
            assert pages[10 * n + i]["text"].split("\n") == want and pages[10 * n + i]["n_dropped"] == 3 - len(want), (n, i)


def test_lines_by_salts(spark, monkeypatch):
    rows = [(i, "http://a.example/", f"same<br>own {i}") for i in range(40)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    want = sorted(map(tuple, line_dedup.drop_boilerplate(df).collect()))
    assert want[0][4].startswith("own")
    for name, value in (("HOT_HOST", 3), ("BROADCAST_LINES", -1)):
        monkeypatch.setattr(line_dedup, name, value)
        assert sorted(map(tuple, line_dedup.drop_boilerplate(df).collect())) == want
    alone = sorted(map(tuple, line_dedup.drop_boilerplate(df, min_holders=41).collect()))
    assert all(r[3] == 0 for r in alone)


URLS = [None, "", "no scheme", "http://x.ORG/a", "https://example.org/es/1?x", "http://sub.example.org/en/12#y", "http://example.org/en/2", "http://notexample.org/es/", "http://a.com/fr/1", "ftp://b.com/de/", "http://org", "http://org/", "http://casino.net/", "http://ads-track.net/x", "http://casinos.net/", "http://u@example.org:80/es/", "a://b://c.org/", "http://a.com?x=/fr/", "http://A.cOm/fr/é"]


def test_urls_against_plain_rules(spark):
    df = spark.createDataFrame([(i, u, "v") for i, u in enumerate(URLS * 2)], "page_id long, url string, verdict string")
    got = {}
    for r in url_filter.filter_urls(df).collect():
        got.setdefault(r["page_id"] % len(URLS), set()).add(tuple(r)[1:])
    for i, u in enumerate(URLS):
        host = path = ""
        if u and "://" in u:
            rest = u.split("://", 1)[1]
            cut = min((rest.find(c) for c in "/?#" if c in rest), default=len(rest))
            host, rest = rest[:cut], rest[cut:]
            host = "".join(c.lower() if c.isascii() else c for c in host)
            path = rest[: min((rest.find(c) for c in "?#" if c in rest), default=len(rest))]
        fits = [(h + p, a) for h, p, a in url_filter.HOST_RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
        best = max(fits, key=lambda f: len(f[0]), default=None)
        bad = not best and any(x in host.replace("-", ".").split(".") for x in ("casino", "adult", "ads"))
        (row,) = got[i]
        assert row[:3] == (host, path, best and best[0]) and row[4] == (best[1] if best else "block" if bad else "allow"), u
    assert url_filter.filter_urls(df.limit(0)).count() == 0 and url_filter.filter_urls(df, (), ()).filter("verdict <> 'allow'").count() == 0
    want = sorted(map(repr, url_filter.filter_urls(df).collect()))
    more = [*url_filter.HOST_RULES, *((f"none{i}.test", "/", "block") for i in range(600))]  # beyond a literal index
    assert sorted(map(repr, url_filter.filter_urls(df, more).collect())) == want
    assert "Python" not in url_filter.filter_urls(df, more)._jdf.queryExecution().toString()


def test_patterns(spark):
    rules = [("two", "^shop^|/sale/*/item^", "block"), ("any", "x*y", "block"), ("path", "|/a.b^", "block")]
    urls = ["http://shop.test/sale/1/item", "http://shop.test/sale//item-3", "http://shops.test/sale/1/item", "http://shop.test/sale/items", "http://my-shop.test/v/sale/q/r/item?z", "http://axby.test/", "http://ab.test/a.b", "http://ab.test/a.bc", "http://ab.test/aab/"]
    got = {r["page_id"]: r["pattern"] for r in url_filter.filter_urls(spark.createDataFrame(list(enumerate(urls)), "page_id long, url string"), (), rules).collect()}
    assert [got[i] for i in range(len(urls))] == ["two", "two", None, None, "two", "any", "path", None, None]
    assert url_filter.pattern_tokens("^shop^|/sale/*/item^") == {"shop", "sale", "item"} and url_filter.pattern_tokens("x*y") == set() and url_filter.pattern_tokens("^cdn.x|/p*q/") == {"cdn"}


def test_rules_are_indexed_by_their_rarest_sure_token():
    assert url_filter.literal_tokens("example.org", "/en/1") == {"example", "org", "en"} and url_filter.literal_tokens("com", "/fr/") == {"com", "fr"} and url_filter.literal_tokens("a.b", "") == {"a", "b"}
    assert url_filter.rarest({"example", "org", "en"}, {"example": 9, "org": 3, "en": 5}) == "org" and url_filter.rarest(set(), {}) == ""
    assert dict((r[1], url_filter.rarest(t, {"pixel": 4, "beacon": 1, "cdn": 90})) for t, r in url_filter.compiled((), url_filter.PATTERN_RULES))["tracking pixels"] == "beacon"


def test_native_operators_run_no_python(spark):
    pages = spark.createDataFrame([(1, "http://a.b/", "<p>x</p>")], "page_id long, url string, html string")
    for df in (url_filter.filter_urls(pages), line_dedup.drop_boilerplate(pages)):
        assert "Python" not in df._jdf.queryExecution().toString() and "Arrow" not in df._jdf.queryExecution().toString()


TEXTS = ["", "a", "it's we'll DON'T 'S x'S", "E\u0301\u0301cole cafe\u0301 Café ça!", "①②3½ x²", "日本語,テスト.", "a\tb\nc  d", "<|endoftext|> x", "\u2260 a=\u0338b", "ΣΑΣ. İstanbul \u212a", "a.\u0301b", "emoji😀.ok", " x y", "...'d 'tis", "ﬁ ǅ. \u0958", "\u00a0x\u2003y", "don't.stop-it(now)1a2"]


def test_pieces_give_the_ids_of_whole_texts():
    plain = Tokenizer.from_file(tokenizer_path())
    encoder = token_output.Encoder(tokenizer_path())
    texts = [t for t in [*TEXTS, "İ.", "ø.Σİ_Z", "\u0958.x", "a\u09dc-b"] if "<|" not in t]
    for text in [*texts, " ".join(texts), "\n".join(texts)]:
        assert encoder.ids(text) == plain.encode(text, add_special_tokens=False).ids, text
    flat, n = encoder.run(texts, 2)
    assert flat.tolist() == [i for t in texts for i in [*plain.encode(t, add_special_tokens=False).ids, 2]] and n.sum() == len(flat)
    encoder.pool, encoder.used = np.zeros(8, np.int32), 0
    encoder.key[:] = 0
    assert encoder.run(texts, 2)[0].tolist() == flat.tolist()  # what is remembered is dropped when full


def test_every_letter_beside_marks():
    import unicodedata

    plain = Tokenizer.from_file(tokenizer_path())
    encoder = token_output.Encoder(tokenizer_path())
    letters = [c for c in map(chr, (*range(0x80, 0xD800), *range(0xE000, 0x30000))) if unicodedata.category(c)[0] == "L"]
    common = [c for c in letters if not (0x3400 <= ord(c) <= 0x9FFF or 0xAC00 <= ord(c) <= 0xD7A3 or ord(c) >= 0x17000)]  # each alone; the rest in rows
    texts = [f"{c}.x_{c}a-{c}" for c in common] + [f"{''.join(letters[i : i + 20])}." + "".join(f"{c}!" for c in letters[i : i + 20]) for i in range(0, len(letters), 20)]
    want = [e.ids for e in plain.encode_batch(texts, add_special_tokens=False)]
    for at in range(0, len(texts), 128):
        flat, n = encoder.documents(texts[at : at + 128], 2)
        assert flat.tolist() == [i for w in want[at : at + 128] for i in [*w, 2]], at


def test_random_texts_have_the_ids_of_the_library():
    rng = random.Random(11)
    plain = Tokenizer.from_file(tokenizer_path())
    encoder = token_output.Encoder(tokenizer_path())
    alphabet = [*"abzAZ019 .,-_!?'\"\n\t", "\u0301", "\u0307", "\u093c", "\u0130", "\u00f8", "\u03a3", "\u03c2", "\u0958", "\u09dc", "\u0a33", "\u1112", "\u1161", "\u11ab", "日", "\u00a0", "½", "😀", "<|endoftext|>", "'s", "'LL"]
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.randrange(1, 12))) for _ in range(20000)]
    flat, n = encoder.documents(texts, 2)
    want = [[*plain.encode(t, add_special_tokens=False).ids, 2] for t in texts]
    got = [x.tolist() for x in np.split(flat, np.cumsum(n)[:-1])]
    assert [t for t, w, g in zip(texts, want, got, strict=True) if w != g] == []


def test_special_strings_have_their_own_ids(spark):
    plain = Tokenizer.from_file(tokenizer_path())
    texts = [*TEXTS, "a <|endoftext|> b", "<|endoftext|>", "x<|startoftext|>Y's<|endoftext|><|endoftext|>", "<|EndOfText|> a", "a <| endoftext |>", "é <|endoftext|>\n日本", "<|endoftext|" + "> w" * 3000]
    want = [[*plain.encode(t, add_special_tokens=False).ids, 2] for t in texts]
    assert want[len(TEXTS)] == [320, 49407, 321, 2]
    encoder = token_output.Encoder(tokenizer_path())
    for _ in range(2):
        flat, sizes = encoder.documents(texts, 2)
        assert flat.tolist() == [i for w in want for i in w] and sizes.tolist() == [len(w) for w in want]
    rows = docs(spark, [(i, t, "en", "s", 0, 0.0, 0) for i, t in enumerate(texts)])
    assert {r["doc_id"]: r["ids"] for r in token_output.encoded(rows, tokenizer_path()).collect()} == dict(enumerate(want))


def test_token_files(spark, tmp_path):
    path = token_output.write_tokens(docs(spark).repartition(5), f"file://{tmp_path}/t", tokenizer_path())
    plain = Tokenizer.from_file(tokenizer_path())
    rows = docs(spark).select("doc_id", "text").collect()
    rows.sort(key=lambda r: (r["doc_id"] is not None, r["doc_id"] or 0))  # equal ids have equal texts here
    at, want = 0, []
    for r in rows:
        ids = [*plain.encode(r["text"] or "", add_special_tokens=False).ids, 2]
        want.append((r["doc_id"], at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        at += len(ids)
    got = sorted(map(tuple, token_output.token_report(spark, path).collect()), key=lambda r: r[1])
    assert got == want
    files = sorted(tmp_path.glob("t/*.orc"))
    meta = [orc.ORCFile(f) for f in files]
    assert all(m.compression == "ZSTD" and m.row_index_stride == 1000 for m in meta) and sum(m.nrows for m in meta) == len(rows)
    assert token_output.token_report(spark, token_output.write_tokens(docs(spark).limit(0), f"file://{tmp_path}/e", tokenizer_path())).count() == 0
    text = token_output.read_tokens(spark, path).filter("doc_id = 4")._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(doc_id), EqualTo(doc_id,4)]" in text


def test_oracles_of_queries(spark):
    from pathloom.llm.queries import ORACLES, QUERIES

    from ..conftest import SF

    c = duckdb.connect()
    for t in ("documents", "embeddings", "pages", "conversations"):
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SF}/{t}.parquet')")
    for name, sql in ORACLES.items():
        r = c.sql(sql)
        mine = QUERIES[name](spark, SF).select(*r.columns)
        key = lambda row: repr([round(x, 6) if isinstance(x, float) else x for x in row])
        assert sorted(map(key, map(tuple, mine.collect()))) == sorted(map(key, r.fetchall())), name
