import zlib
from collections import defaultdict

import numpy as np
import pytest

from joinsynth.llm import quality_classifier as qc

from .test_dedup import brute_near, brute_passages
from .test_first_five import brute_hits

SF = "/root/testdata/sf0.01"


def test_views_and_combination(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.1/labels.parquet")
    got = qc.classify(docs, labels.filter("doc_id % 10 < 7")).join(labels.filter("doc_id % 10 >= 7").withColumnsRenamed({"quality": "is_good", "toxic": "is_toxic"}), "doc_id").toPandas()
    right = {c: ((got[c] >= 0.5) == got["is_good" if c.startswith("quality") else "is_toxic"]).mean() for c in ("quality", "quality_text", "quality_page", "toxic", "toxic_text")}
    assert right["quality"] > 0.97 and right["toxic"] > 0.95
    assert right["quality"] >= max(right["quality_text"], right["quality_page"]) - 0.01


def test_odd_tables(spark, odd_docs, no_docs):
    none = spark.createDataFrame([], "doc_id bigint, quality int, toxic int")
    assert qc.classify(odd_docs, none).filter("accepted").count() == odd_docs.count()
    assert qc.classify(no_docs, none).count() == 0
    labels = spark.read.parquet(f"{SF}/labels.parquet").unionByName(spark.createDataFrame([(None, 1, 0), (0, None, None)], "doc_id bigint, quality int, toxic int"))
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", "lang", "source").unionByName(odd_docs.select("doc_id", "text").selectExpr("doc_id + 100000 as doc_id", "text", "null as lang", "null as source"))
    out = qc.classify(docs, labels)
    assert out.count() == docs.count() and out.filter("quality is null or toxic is null").count() == 0
    assert qc.accepted_only(docs, labels).count() == out.filter("accepted").count()


def made_features(bags, places, labels):
    edges = np.concatenate([[0], np.cumsum([len(b) for b in bags])])
    return qc.Features(np.concatenate(bags), edges, np.zeros((len(bags), qc.LAYOUT)), np.array(places), np.stack([labels, np.full(len(bags), -1)], 1))


def test_exchange_helps_the_weaker_view():
    """Metadata tells the class, few labels hold the words: the page view's pseudo-labels teach the text view words that no label has."""
    rng = np.random.default_rng(0)
    n = 4000
    y = rng.integers(0, 2, n)
    places = [(int(c) if rng.random() < 0.99 else int(1 - c), 64 + int(rng.integers(0, 8)), 128 + int(rng.integers(0, 8))) for c in y]
    bags = [np.unique(rng.integers(0, 200, 4) + 200 * c).astype(np.int32) for c in y]
    labels = np.where(np.arange(n) < 150, y, -1)
    known = made_features(bags[:150], places[:150], labels[:150])
    free, rest = (made_features(bags[a:b], places[a:b], labels[a:b]) for a, b in ((150, 2500), (2500, n)))
    rounds = []

    def taught_by(models):
        rounds.append(models[0].text.logit(rest))
        return [qc.pseudo_counts(free, 0, models[0]), [(np.zeros((2, s)), np.zeros(2)) for s in (1 << qc.BITS, qc.PLACES)]]

    model = qc.co_train(known, taught_by)[0]
    right = lambda z: ((z >= 0) == y[2500:]).mean()
    assert right(model.text.logit(rest)) > max(0.97, right(rounds[0]) + 0.02)
    assert ((model.probabilities(rest)[2] >= 0.5) == y[2500:]).mean() > 0.97


def test_query_matches_one_process(spark):
    """The rounds over the whole corpus as a plain loop over documents."""
    docs, labels = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("documents", "labels"))
    given = {r.doc_id: (r.quality, r.toxic) for r in labels.collect()}
    rows = docs.select("doc_id", "text", "lang", "source", "n_chars").collect()
    bags, layout, places = [qc.text_features(r.text) for r in rows], [qc.layout_features(r.text) for r in rows], [qc.page_places(r.lang, r.source, r.n_chars) for r in rows]
    x = qc.Features(np.concatenate(bags), np.concatenate([[0], np.cumsum([len(b) for b in bags])]), np.array(layout, float), np.array(places), np.array([given.get(r.doc_id, (-1, -1)) for r in rows]))
    _, known = qc.featurise(docs, labels)

    def taught_by(models):
        out = []
        for t, m in enumerate(models):
            words, values = [np.zeros((2, s)) for s in (1 << qc.BITS, qc.PLACES)]
            n = np.zeros((2, 2))
            for i in np.flatnonzero(x.labels[:, t] < 0).tolist():
                one = x.take(np.array([i]))
                for k, (view, table, own) in enumerate(((m.page, words, bags[i]), (m.text, values, places[i]))):
                    p = 1 / (1 + np.exp(-view.logit(one)[0]))
                    if p >= qc.SURE or p <= 1 - qc.SURE:
                        table[int(p >= qc.SURE), own] += 1
                        n[k, int(p >= qc.SURE)] += 1
            out.append([(words, n[0]), (values, n[1])])
        return out

    want = qc.probabilities(x, qc.co_train(known, taught_by))
    got = {r.doc_id: r for r in qc.classify(docs, labels).collect()}
    for i, r in enumerate(rows):
        assert np.allclose([got[r.doc_id][c] for c in qc._SCORE_NAMES[1:]], [p[i] for p in want], atol=1e-9)
        assert got[r.doc_id].accepted == (want[2][i] >= 0.5 and want[5][i] < 0.4)


def test_pipeline_matches_its_brute_force_version(spark, monkeypatch):
    import public_tokenizers
    from tokenizers import Tokenizer

    import corpus_pipeline

    rows = spark.read.parquet(f"{SF}/documents.parquet").collect()
    folder = {}

    def reading(s, path, name):
        folder[name] = folder.get(name, 0) + 1
        return s.read.parquet(f"{path}/{name}.parquet")

    monkeypatch.setattr(corpus_pipeline, "table", reading)
    packed = corpus_pipeline.run(spark, SF).collect()
    assert folder["documents"] == 1
    accepted = {r.doc_id for r in qc.classify(spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")).filter("accepted").collect()}
    docs = [(r.doc_id, r.text) for r in rows if r.doc_id in accepted]
    before = dict(docs)
    docs = [(d, t) for d, t in brute_passages(docs).items() if t or t == before[d]]
    near = brute_near(docs)
    docs = [(d, t) for d, t in docs if near[d][2]]
    items = [tuple(r) for r in spark.read.parquet(f"{SF}/benchmark.parquet").select("item_id", "text").collect()]
    hit = {r[0] for r in brute_hits(docs, items) if r[-1]}
    docs = {d: t for d, t in docs if d not in hit}
    assert {r.doc_id for r in packed} == set(docs) and hit
    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    pieces = defaultdict(dict)
    for r in packed:
        pieces[r.doc_id][r.start] = r
    for d, t in list(docs.items())[::20]:
        ids, at = np.array([*library.encode(t, add_special_tokens=False).ids, 1], "<u4"), 0
        for start in sorted(pieces[d]):
            r = pieces[d][start]
            assert start == at and r.ids_crc32 == zlib.crc32(ids[at : at + r.length].tobytes())
            at += r.length
        assert at == len(ids)


@pytest.mark.parametrize("k", range(4))
def test_stages_keep_columns_and_survive_odd_rows(spark, odd_docs, k):
    import corpus_pipeline

    docs = odd_docs.selectExpr("doc_id", "text", "cast(null as string) as lang", "'s' as source", "cast(length(text) as bigint) as n_chars")
    _, stage = corpus_pipeline.STAGES[k]
    out = stage(spark, docs, SF)
    assert out.columns == docs.columns and [f.dataType for f in out.schema] == [f.dataType for f in docs.schema]
    ids = {r.doc_id for r in out.collect()}
    if k:
        assert {3, 4, 5, 10, None} <= ids and (2 in ids) == (k != 2)
    assert stage(spark, docs.limit(0), SF).count() == 0


def test_near_stage_keeps_one_row_of_repeated_ones(spark):
    import corpus_pipeline

    text, other = " ".join(f"word{i}" for i in range(60)), " ".join(f"other{i}" for i in range(60))
    rows = [(5, text), (5, text), (7, text), (None, text), (None, other), (None, other), (9, None), (9, None), (11, "short")]
    docs = spark.createDataFrame([(i, t, "en", "s", 1) for i, t in rows], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    out = sorted(((r.doc_id or -1), r.text or "") for r in corpus_pipeline.near(spark, docs, SF).collect())
    assert out == [(-1, other), (5, text), (9, ""), (11, "short")]
