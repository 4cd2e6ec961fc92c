import hashlib
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from joinsynth.llm import decontamination as dc
from pyspark.sql import functions as F

from joinsynth.llm import packing, sharding, token_counts, url_filters
from joinsynth.llm.queries import URL_RULES, tokenizer_path

SF = "/root/testdata/sf0.001"
DOC = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def brute_hits(docs, items, window=10):
    spans = [(i, DOC.findall((t or "").translate(LOWER))) for i, t in items]
    for doc, text in docs:
        w = DOC.findall((text or "").translate(LOWER))
        hit, found = set(), set()
        for name, own in spans:
            k = min(window, len(own))
            windows = {tuple(own[j : j + k]) for j in range(len(own) - k + 1)} if own else set()
            for j in range(len(w) - k + 1 if own else 0):
                if tuple(w[j : j + k]) in windows:
                    hit.update(range(j, j + k))
                    found.add(name)
        names = sorted(str(x) for x in found if x is not None)
        yield doc, len(w), len(hit), len(found), hashlib.sha256(",".join(names).encode()).hexdigest(), bool(hit)


@pytest.mark.parametrize("block", [1 << 24, 700])
def test_decontamination(spark, odd_docs, no_docs, monkeypatch, block):
    monkeypatch.setattr(dc, "BLOCK_BYTES", block)
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").unionByName(odd_docs.select("doc_id", "text"))
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").limit(12).collect()] + [(900, "lazy dog"), (901, "one"), (902, None), (903, "..."), (904, "lorem ipsum dolor lorem ipsum dolor lorem ipsum dolor lorem ipsum dolor")]
    items += [(900, "quick brown fox"), (900, "lazy dog"), (None, "lazy dog"), (None, "brown fox jumps")]
    got = dc.contamination_report(docs, spark.createDataFrame(items, "item_id bigint, text string"))
    want = list(brute_hits([tuple(r) for r in docs.collect()], items))
    assert Counter(map(tuple, got.collect())) == Counter(want)
    assert any(w[-1] for w in want)
    assert dc.contamination_report(no_docs, spark.createDataFrame(items, "item_id bigint, text string")).count() == 0
    empty = spark.createDataFrame([], "item_id bigint, text string")
    assert dc.contamination_report(odd_docs, empty).filter("contaminated").count() == 0
    assert dc.decontaminate(odd_docs, empty).count() == odd_docs.count()


def test_suffix_array_and_longest_match(spark):
    rng = np.random.default_rng(5)
    ids = rng.integers(-1, 3, 400)
    sa = dc.suffix_array(ids)
    until = lambda p: tuple(ids[p : p + np.flatnonzero(np.append(ids[p:], -1) < 0)[0]])
    keys = [until(p) for p in sa]
    assert sorted(keys) == keys and sorted(sa) == np.flatnonzero(ids >= 0).tolist()
    docs = spark.createDataFrame([(1, "a b c d e"), (2, "x b c d")], "doc_id bigint, text string")
    got = dc.longest_matches(docs, spark.createDataFrame([(7, "b c d e f")], "item_id bigint, text string"))
    assert {(r.word, r.longest, r.doc_id) for r in got.collect()} == {(0, 4, 1), (1, 3, 1), (2, 2, 1), (3, 1, 1)}


def test_token_counts(spark, odd_docs, no_docs):
    from tokenizers import Tokenizer

    path = tokenizer_path("word_bpe_49k.json")
    library = Tokenizer.from_file(path)
    docs = odd_docs.select("doc_id", "text").unionByName(spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text"))
    want = Counter((d, len((t or "").encode()), n := len(library.encode(t or "", add_special_tokens=False).ids), n > 2048) for d, t in docs.collect())
    assert Counter(map(tuple, token_counts.count_tokens(docs, path).collect())) == want
    assert token_counts.count_tokens(no_docs, path).count() == 0


def test_heap_merging_takes_the_lowest_rank_first():
    rank = {("a", "b"): 1, ("b", "c"): 0, ("a", "bc"): 2}
    assert token_counts.merge_count(list("abc"), rank) == 2
    assert token_counts.merge_count(list("aaaa"), {("a", "a"): 0, ("aa", "aa"): 1}) == 3
    assert token_counts.merge_count(list("aaa"), {("a", "a"): 0}) == 1


def test_packing_round_trip(spark, odd_docs, no_docs):
    from tokenizers import Tokenizer

    path = tokenizer_path("byte_bpe_50k.json")
    library = Tokenizer.from_file(path)
    docs = odd_docs.filter("doc_id is not null").select("doc_id", "text").distinct().unionByName(spark.read.parquet(f"{SF}/documents.parquet").selectExpr("doc_id + 1000 as doc_id", "text"))
    ids = {d: np.array([*library.encode(t or "", add_special_tokens=False).ids, 1], "<u4") for d, t in docs.collect()}
    rows = packing.pack(docs, path).collect()
    by_doc, by_seq = defaultdict(list), defaultdict(list)
    for r in rows:
        own = ids[r.doc_id]
        assert r.doc_tokens == len(own) and r.ids_crc32 == zlib.crc32(own[r.start : r.start + r.length].tobytes())
        by_doc[r.doc_id].append((r.start, r.length))
        by_seq[r.sequence_id].append((r.offset, r.length))
    for spans, size in ((by_doc, {d: len(x) for d, x in ids.items()}), (by_seq, None)):
        for k, own in spans.items():
            at = 0
            for start, length in sorted(own):
                assert start == at
                at += length
            assert at == size[k] if size else at <= 2048
    totals = [sum(n for _, n in own) for own in by_seq.values()]
    padding = sum(2048 - t for t in totals if t & (t - 1))
    assert padding < 0.03 * sum(totals)
    assert len(packing.pack(odd_docs, path).filter("doc_id = 8 and start = 0").collect()) == 2
    assert packing.pack(no_docs, path).count() == 0


def test_url_rules_and_aliases(spark):
    canonical = "<html><head><link rel='canonical' href='{}'></head>"
    refresh = '<meta http-equiv="refresh" content="0; url={}">'
    pages = [
        (1, "http://A.Example.org/es/x?q=/en/1", None), (2, "https://example.org/en/12", ""), (3, "https://notexample.org/en/1", ""), (4, None, ""), (5, "no scheme", "<p>"),
        (6, "https://x.net/a", canonical.format("https://shop.com/de/1")), (7, "https://y.net/b", refresh.format("https://x.net/a")), (8, "https://good.com/fr/1", canonical.format("https://x.net/a")),
        (9, "https://z.net/free", canonical.format("/other")), (10, "ftp://q.net#f", ""), (10, "ftp://q.net#f", ""),
    ]
    frame = spark.createDataFrame([(*p, "x") for p in pages], "page_id bigint, url string, html string, rule string")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_filters.judge_urls(frame, URL_RULES).collect()}
    assert got == {
        1: ("a.example.org", "/es/x", "example.org/es/", "block"), 2: ("example.org", "/en/12", "example.org/en/1", "block"), 3: ("notexample.org", "/en/1", "org/", "allow"),
        4: ("", "", None, "allow"), 5: ("", "", None, "allow"), 6: ("x.net", "/a", None, "block"), 7: ("y.net", "/b", None, "block"), 8: ("good.com", "/fr/1", "com/fr/", "allow"),
        9: ("z.net", "/free", None, "allow"), 10: ("q.net", "", None, "allow"),
    }
    group = {r.page_id: r.verdict for r in url_filters.judge_urls(frame, URL_RULES, allow_wins="group").collect()}
    assert (group[6], group[7]) == ("allow", "allow")
    many = [*URL_RULES, *(url_filters.Rule("block", f"h{i}.test", "/") for i in range(80))]
    assert {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_filters.judge_urls(frame, many).collect()} == got
    assert url_filters.judge_urls(frame.limit(0), URL_RULES).count() == 0


def test_links_meet_their_pages_in_every_form(spark):
    """Each target is a blocked page; the linking page has no rule of its own and must be blocked with it."""
    from urllib.parse import urljoin

    rules = [url_filters.Rule("block", "example.org", "/x/")]
    base = "http://site.net/x/d/a?q=1"
    bad = [f"http://example.org/x/{k}?page=2&ref=x" for k in range(6)]
    canonical, refresh = '<link rel="canonical" href="{}">', '<meta http-equiv="refresh" content="0; url={}">'
    forms = [(bad[0].replace("&", "&amp;"), canonical), (bad[1].replace("&", "&#38;"), canonical), (bad[2].replace("&", "&#x26;"), canonical),
             (bad[3].replace("&", "&amp;"), refresh), (bad[4].replace("http://example", "HTTP://EXAMPLE"), canonical), ("http://example.org/y/../x/./5?page=2&ref=x", canonical)]
    pages = [(k, f"http://from{k}.net/", tag.format(t), None) for k, (t, tag) in enumerate(forms)] + [(100 + k, u, "", None) for k, u in enumerate(bad)]
    # relative forms: the page and what it names are aliases, and the named page points to a blocked one
    relative = ["b.html", "?p=2", "../x", "./c", "/r", "../../../t", "//other.net/z", "d/", "g?y/../z"]
    for k, form in enumerate(relative):
        here = base.replace("site", f"Site{k}")
        pages += [(200 + k, here, canonical.format(form), None), (300 + k, urljoin(here, form).replace("Site", "sITE"), refresh.format(bad[0]) if form != "//other.net/z" else canonical.format(bad[0]), None)]
    # no edge: another scheme, a fragment, a url inside a query
    pages += [(400, "http://free.net/a", canonical.format("mailto:x@example.org"), None), (401, "http://free.net/b", canonical.format("#top"), None), (402, "http://free.net/c", canonical.format(f"/l?to={bad[0]}"), None)]
    frame = spark.createDataFrame(pages, "page_id bigint, url string, html string, rule string")
    got = {r.page_id: r.verdict for r in url_filters.judge_urls(frame, rules).collect()}
    assert {k for k, v in got.items() if v == "allow"} == {400, 401, 402}
    text = "a&amp;b&amp;lt;&lt;&copy=1&eacute;&#233;&#xE9;&nope;&#55555555;&&amp"
    assert spark.range(1).select(url_filters.unescaped(F.lit(text))).first()[0] == "a&b&lt;<&copy=1ééé&nope;&#55555555;&&"
    table = spark.createDataFrame([("HTTP://Gone.net/o", bad[0])], "a string, b string")
    gone = spark.createDataFrame([(1, "http://gone.NET/o#f", "")], "page_id bigint, url string, html string")
    assert url_filters.judge_urls(gone, rules, redirects=table).first().verdict == "block"
    several = spark.createDataFrame([(1, "http://s.net/", canonical.format("/own") + "<p>" + canonical.format(bad[0])), (2, "http://t.net/", refresh.format("/u") + refresh.format(bad[1]))], "page_id bigint, url string, html string")
    assert [r.verdict for r in url_filters.judge_urls(several, rules).collect()] == ["block", "block"]


def test_aliases_by_a_shuffle(spark, monkeypatch):
    monkeypatch.setattr(url_filters, "BROADCAST_BYTES", 0)
    test_url_rules_and_aliases(spark)


EXTREME = {"blanks": " " * 2_000_000, "line ends": "\n" * 2_000_000, "letter": "a" * 2_000_000, "symbol": "-" * 2_000_000, "mixed": "word " * 5_000 + "\t" * 1_000_000 + "é" * 600_000 + "\r\n" * 300_000}


def test_extreme_runs_give_the_library_s_ids(spark):
    from tokenizers import Tokenizer

    path, words = tokenizer_path("byte_bpe_50k.json"), tokenizer_path("word_bpe_49k.json")
    encoder, library = packing.ByteLevelEncoder(path), Tokenizer.from_file(path)
    for text in EXTREME.values():
        assert encoder.encode(text).tolist() == library.encode(text, add_special_tokens=False).ids
    docs = spark.createDataFrame(list(enumerate(EXTREME.values())), "doc_id bigint, text string")
    size = {r.doc_id: r.doc_tokens for r in packing.pack(docs, path).collect()}
    assert size == {i: len(library.encode(t, add_special_tokens=False).ids) + 1 for i, t in enumerate(EXTREME.values())}
    other = Tokenizer.from_file(words)
    counts = {r.doc_id: r.n_tokens for r in token_counts.count_tokens(docs, words).collect()}
    assert counts == {i: len(other.encode(t, add_special_tokens=False).ids) for i, t in enumerate(EXTREME.values())}
    items = spark.createDataFrame([(1, "word word word")], "item_id bigint, text string")
    assert dc.contamination_report(docs, items).filter("contaminated").count() == 1


def test_sharding(spark, odd_docs, no_docs):
    docs = spark.range(3000).selectExpr("id as doc_id", "case when id % 3 = 0 then repeat('same ', 50) else repeat(cast(id as string), cast(id % 90 as int)) end as text", "id as size")
    for frame in (docs, odd_docs):
        rows = sharding.shard_by_bytes(frame, 24).collect()
        want = Counter((d, len((t or "").encode()) + 8, zlib.crc32((t or "").encode())) for d, t in frame.select("doc_id", "text").collect())
        assert Counter((r.doc_id, r.size, r.text_crc32) for r in rows) == want
        slots = defaultdict(list)
        for r in rows:
            slots[r.shard].append(r.slot)
            assert r.law == "bytes" and 0 <= r.shard < 24 and r.grown_shard is None
        assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    size = Counter()
    for r in sharding.shard_by_bytes(docs, 24).collect():
        size[r.shard] += r.size
    mean = sum(size.values()) / 24
    assert len(size) == 24 and max(abs(s / mean - 1) for s in size.values()) < 0.05
    assert sharding.shard_by_bytes(no_docs, 24).count() == 0


def test_sharding_ranges_finer_than_shards(spark, monkeypatch):
    monkeypatch.setattr(sharding, "RANGE_ROWS", 20)
    rows = sharding.shard_by_bytes(spark.range(2000).selectExpr("id as doc_id", "cast(id as string) as text"), 4).collect()
    slots = defaultdict(list)
    for r in rows:
        slots[r.shard].append(r.slot)
    assert sorted(slots) == [0, 1, 2, 3] and all(sorted(s) == list(range(len(s))) for s in slots.values())
