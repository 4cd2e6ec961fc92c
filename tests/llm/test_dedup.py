import hashlib
import random
import re
from collections import Counter

import numpy as np
import pytest

from joinsynth.llm import embedding_dedup as ed
from joinsynth.llm import line_dedup, minhash_dedup
from joinsynth.llm import substring_dedup as sd
from joinsynth.llm.components import components
from joinsynth.llm.shingles import shingle_set


def least_reachable(ids, links):
    parent = {i: i for i in ids}

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for a, b in links:
        a, b = sorted((root(a), root(b)))
        parent[b] = a
    return {i: root(i) for i in ids}


def test_components(spark):
    rng = random.Random(3)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(1000, 1100)] + [(7, 7), (None, 3), (5, None)]
    got = {r.v: r.component for r in components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()}
    ends = {x for a, b in edges if a is not None and b is not None and a != b for x in (a, b)}
    want = least_reachable(ends, [(a, b) for a, b in edges if a in ends and b in ends and a != b])
    assert got == {v: c for v, c in want.items() if v != c}
    assert components(spark.createDataFrame([], "a bigint, b bigint")).count() == 0


@pytest.mark.parametrize("one_task", [0, 40, 500_000])
def test_components_by_rounds_and_in_one_task_agree(spark, monkeypatch, one_task):
    """Paths, stars, rings and negative ids; by rounds only, by rounds and then one task, and in one task."""
    from joinsynth.llm import components as c

    monkeypatch.setattr(c, "ONE_TASK", one_task)
    edges = [(i, i + 1) for i in range(-40, 20)] + [(100, 100 + i * 7) for i in range(1, 30)] + [(1000 + i, 1000 + (i + 5) % 16) for i in range(16)] + [(None, 5), (6, None), (3000, 3000)]
    got = {r.v: r.component for r in components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()}
    assert got == {**{i: -40 for i in range(-39, 21)}, **{100 + i * 7: 100 for i in range(1, 30)}, **{1000 + i: 1000 for i in range(1, 16)}}


def test_components_of_few_edges_take_few_jobs(spark):
    """A long path took a dozen jobs a round, each with plans and exchange threads on the driver."""
    context = spark.sparkContext
    edges = spark.createDataFrame([((i * 37) % 301, ((i + 1) * 37) % 301) for i in range(300)], "a bigint, b bigint")
    context.setJobGroup("few-edges", "components")
    try:
        assert components(edges).filter("component = 0").count() == 300
        jobs = len(context.statusTracker().getJobIdsForGroup("few-edges"))
    finally:
        context.setLocalProperty("spark.jobGroup.id", None)
    assert jobs <= 10


def shingles(text):
    w = [x for x in re.split(r"[\x20\x09-\x0D]+", (text or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))) if x]
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()


def brute_near(docs):
    sets = {d: shingles(t) for d, t in docs}
    ids = sorted(sets)
    links = [(a, b) for k, a in enumerate(ids) for b in ids[k + 1 :] if sets[a] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])]
    reach = least_reachable(ids, links)
    return {d: (len(sets[d]), reach[d], reach[d] == d) for d in ids}


@pytest.mark.parametrize("block", [64, 3])
def test_minhash_near_duplicates(spark, monkeypatch, block):
    monkeypatch.setattr(minhash_dedup, "BLOCK", block)
    rng = random.Random(11)
    words = [f"w{i}" for i in range(400)]
    docs, base = [], [rng.choice(words) for _ in range(120)]
    for d in range(60):  # a chain of edits: neighbours are linked, ends are not
        base = list(base)
        base[rng.randrange(len(base))] = rng.choice(words)
        docs.append((d, " ".join(base)))
    shared = " ".join(rng.choice(words) for _ in range(60))
    docs += [(100 + d, shared + " " + " ".join(rng.choice(words) for _ in range(40))) for d in range(40)]
    docs += [(200, docs[5][1]), (201, docs[5][1].upper()), (202, None), (203, ""), (204, " \t"), (205, "a b c"), (206, "A  b\nc"), (207, "a b c d"), (208, "x " * 30000)]
    frame = spark.createDataFrame([(*d, 1, "p") for d in docs], "doc_id bigint, text string, p1 int, sig string").repartition(5)
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in minhash_dedup.near_duplicates(frame).collect()}
    assert got == brute_near(docs)


def test_minhash_odd_tables(spark, odd_docs, no_docs):
    rows = minhash_dedup.near_duplicates(odd_docs).collect()
    assert len(rows) == odd_docs.count()
    by = {r.doc_id: r for r in rows}
    assert by[2].component_id == 1 and not by[2].kept and by[8].kept and by[3].kept and by[None].component_id is None and by[None].kept
    assert minhash_dedup.near_duplicates(no_docs).count() == 0


def test_shingle_counts_match_sets():
    rng = random.Random(2)
    for _ in range(200):
        text = "".join(rng.choice(["a", "B", "é", " ", "  ", "\n", "\x0b", "\xa0", "zz "]) for _ in range(rng.randrange(60)))
        assert len(shingle_set(text)) == len(shingles(text))


def brute_cut(docs):
    raws = [(d, (t or "").encode()) for d, t in docs]
    seen = Counter(r[i : i + 200] for _, r in raws for i in range(len(r) - 199))
    for d, r in raws:
        cover = np.zeros(len(r), bool)
        for i in range(len(r) - 199):
            if seen[r[i : i + 200]] > 1:
                cover[i : i + 200] = True
        left = bytes(np.frombuffer(r, np.uint8)[~cover])
        yield d, len(r), int(cover.sum()), int((cover & ~np.append(False, cover[:-1])).sum()) if len(r) else 0, hashlib.sha256(left).hexdigest()


@pytest.mark.parametrize("hot", [200, 2])
def test_substring_dedup(spark, odd_docs, no_docs, monkeypatch, hot):
    monkeypatch.setattr(sd, "HOT", hot)
    rng = random.Random(4)
    rand = lambda n: "".join(rng.choice("abcdeé \n") for _ in range(n))
    passage, other = rand(330), rand(210)
    docs = [(d, rand(rng.randrange(300)) + passage[: rng.randrange(150, 330)] + rand(rng.randrange(300))) for d in range(25)]
    docs += [(50, other + other), (51, other[:199]), (52, "x" * 450), (53, "x" * 199), (54, rand(900)), (55, "\x00" * 300 + "end"), (56, "ab" * 300)]
    docs += [(60, docs[3][1]), (61, docs[3][1][:250] + "!" + docs[3][1][250:])] + [tuple(r) for r in odd_docs.select("doc_id", "text").collect()]
    frame = spark.createDataFrame([(*d, 5, "s") for d in docs], "doc_id bigint, text string, key int, span string").repartition(4)
    out = sd.cut_repeats(frame)
    got = Counter(tuple(r) for r in out.drop("kept").collect())
    assert got == Counter(brute_cut(docs))
    assert all(hashlib.sha256(r.kept).hexdigest() == r.kept_sha256 for r in out.collect())
    assert sd.cut_repeats(no_docs).count() == 0


def test_crowds_whose_contexts_share_a_few_bytes(spark, monkeypatch):
    monkeypatch.setattr(sd, "HOT", 12)
    rng = random.Random(6)
    rand = lambda n: "".join(rng.choice("abcdefgh") for _ in range(n))
    passage = rand(190)
    families = [(rand(30), rand(30)) for _ in range(12)]
    docs = []
    for left, right in families:
        docs += [(len(docs) + k, rand(20 + k) + left + passage + right + rand(20 + k)) for k in range(6)]
        docs += [(len(docs) + k, rand(40) + left[30 - k :] + passage + right[: rng.randrange(10, 16)] + rand(40)) for k in range(1, 16)]
        docs += [(len(docs) + k, rand(40) + left[30 - rng.randrange(10, 16) :] + passage + right[:k] + rand(40)) for k in range(1, 16)]
    docs = [(d, t) for d, (_, t) in enumerate(docs)]
    frame = spark.createDataFrame(docs, "doc_id bigint, text string").repartition(2)
    assert Counter(tuple(r) for r in sd.cut_repeats(frame).drop("kept").collect()) == Counter(brute_cut(docs))


def test_two_stage_order_is_the_suffix_order():
    rng = np.random.default_rng(7)
    for size, letters in ((1, 2), (50, 2), (400, 2), (400, 5), (900, 200)):
        text = np.append(rng.integers(1, letters + 1, size), 0).astype(np.uint8)
        raw = text.tobytes()
        sa = sd.two_stage_order(text, 1024)
        assert sa.tolist() == sorted(range(len(raw)), key=lambda i: raw[i:])
        share = sd.neighbours_share(text, sa, 3)
        assert [bool(s) for s in share[1:]] == [raw[a : a + 3].ljust(3, b"\0") == raw[b : b + 3].ljust(3, b"\0") for a, b in zip(sa, sa[1:], strict=False)]


def brute_chunks(docs):
    """Numbers of coarse chunks by the stated rule, and of those that occurred before by (id, place)."""
    seen, out = set(), {}
    for d, text in sorted(docs):
        hashes = [int(hashlib.md5(x.encode()).hexdigest()[:15], 16) for x in text.split("\n")]
        lines, chunks, own = text.split("\n"), [], []
        for i, line in enumerate(lines):
            own.append(line)
            roll = hashes[i] ^ (hashes[i - 1] >> 1 if i else 0) ^ (hashes[i - 2] >> 2 if i > 1 else 0)
            if i == len(lines) - 1 or roll % 4 == 0:
                chunks.append(own)
                own = []
        gone = 0
        for c in chunks:
            if sum(bool(x.strip(" ")) for x in c) >= 2:
                gone += "\n".join(c) in seen
                seen.add("\n".join(c))
        out[d] = (len(lines), len(chunks), gone)
    return out


def brute_passages(docs):
    """Without the lines of every pair of neighbouring lines (blank ones between them aside) that occurred before, by (id, place)."""
    seen, out = set(), {}
    for d, text in sorted(docs):
        lines, gone = text.split("\n"), set()
        full = [i for i, x in enumerate(lines) if x.strip(" ")]
        for s, e in zip(full, full[1:], strict=False):
            unit = "\n".join(lines[s : e + 1])
            if unit in seen:
                gone |= set(range(s, e + 1))
            seen.add(unit)
        out[d] = "\n".join(x for i, x in enumerate(lines) if i not in gone)
    return out


def test_line_dedup(spark, odd_docs, no_docs):
    rng = random.Random(9)
    pool = [[f"line {k} {i}" for i in range(rng.randrange(2, 12))] for k in range(12)]
    docs = []
    for d in range(60):
        lines = []
        for _ in range(rng.randrange(1, 5)):
            lines += rng.choice(pool) if rng.random() < 0.6 else [f"own {rng.random()}" for _ in range(rng.randrange(1, 5))]
            lines += [""] * rng.randrange(3)
        docs.append((d, "\n".join(lines)))
    docs.append((99, docs[0][1]))
    frame = spark.createDataFrame([(*d, 3) for d in docs], "doc_id bigint, text string, at int").repartition(4)
    out = line_dedup.dedup_lines(frame).collect()
    assert {r.doc_id: r.text for r in out} == brute_passages(docs)
    assert {r.doc_id: (r.ld_lines, r.ld_chunks, r.ld_removed) for r in out} == brute_chunks(docs)
    assert sum(r.ld_removed for r in out) > 10
    coarse = {r.doc_id: (r.text, r.ld_removed) for r in line_dedup.dedup_lines(frame, finest=False).collect()}
    assert all(len(t) >= len(dict((r.doc_id, r.text) for r in out)[d]) for d, (t, _) in coarse.items()) and {d: n for d, (_, n) in coarse.items()} == {r.doc_id: r.ld_removed for r in out}
    odd = {(r.doc_id, r.text, r.ld_removed) for r in line_dedup.dedup_lines(odd_docs).select("doc_id", "text", "ld_removed").collect()}
    assert (3, None, 0) in odd and (4, "", 0) in odd and {r[0] for r in odd} == {1, 2, 3, 4, 5, 6, 7, 8, 9, 10, None}
    assert line_dedup.dedup_lines(no_docs).count() == 0


@pytest.mark.parametrize("most", [2048, 40])
def test_embedding_near_duplicates(spark, monkeypatch, most):
    monkeypatch.setattr(ed, "BLOCK_MOST", most)
    rng = np.random.default_rng(1)
    rows = [rng.normal(size=8) for _ in range(150)]
    for spread, n in ((0.02, 60), (0.16, 60), (0.3, 40)):
        centre = rng.normal(size=8)
        centre /= np.linalg.norm(centre)
        rows += [centre + spread * rng.normal(size=8) for _ in range(n)]
    rows += [rows[0], rows[0] * 3, rows[5]]
    data = [(i, r.astype(np.float32).tolist()) for i, r in enumerate(rows)]
    n = len(data)
    data += [(n, None), (n + 1, [0.0] * 8), (n + 2, [float("nan")] * 8), (n + 3, [1.0, None] * 4), (n + 4, []), (n + 5, [float("inf")] * 8), (n + 6, [1.0, 2.0]), (n + 7, [2.0, 4.0])]
    frame = spark.createDataFrame([(*d, 1) for d in data], "vec_id bigint, embedding array<float>, weight int").repartition(3)
    x = np.array([r.astype(np.float32) for r in rows], float)
    x /= np.linalg.norm(x, axis=1)[:, None]
    near = x @ x.T >= 0.9
    np.fill_diagonal(near, False)
    links = [*zip(*np.nonzero(near), strict=True), (n + 6, n + 7)]
    reach = least_reachable(range(n + 8), [(int(a), int(b)) for a, b in links])
    want = {i: (int(near[i].sum()) if i < n else int(i >= n + 6), reach[i], reach[i] == i) for i in range(n + 8)}
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in ed.embedding_near_duplicates(frame).collect()}
    assert got == want
    assert ed.embedding_near_duplicates(frame.limit(0)).count() == 0
    twice = ed.embedding_near_duplicates(spark.createDataFrame([(None, [1.0, 0.0]), (4, [1.0, 0.0]), (4, [1.0, 0.0])], "vec_id bigint, embedding array<float>")).collect()
    assert sorted((r.vec_id or 0, r.n_links) for r in twice) == [(0, 0), (4, 1), (4, 1)]


def test_passages_of_two_to_eight_lines(spark, odd_docs, no_docs):
    rng = random.Random(4)
    passages = [[f"passage {k} line {i} " + "word " * 12 for i in range(k % 7 + 2)] for k in range(70)]
    docs = []
    for d in range(200):
        lines = [f"own {rng.random()}" for _ in range(rng.randrange(1, 4))]
        for _ in range(2):
            lines += [*rng.choice(passages), *([""] * rng.randrange(2)), f"own {rng.random()}"]
        docs.append((d, "\n".join(lines)))
    docs.append((900, "\n".join(f"line {i} {'x' * (i % 3)}" for i in range(20_000))))
    docs.append((901, docs[-1][1]))
    frame = spark.createDataFrame([(*d, 3) for d in docs], "doc_id bigint, text string, at int").repartition(4)
    out = {r.doc_id: r.text for r in line_dedup.dedup_lines(frame).collect()}
    assert out == brute_passages(docs)
    for p in passages:
        body = "\n".join(p)
        assert sum(body in t for t in out.values()) <= 1
    odd = {(r.doc_id, r.text, r.ld_removed_lines) for r in line_dedup.dedup_lines(odd_docs).select("doc_id", "text", "ld_removed_lines").collect()}
    assert (3, None, 0) in odd and (4, "", 0) in odd and {r[0] for r in odd} == {1, 2, 3, 4, 5, 6, 7, 8, 9, 10, None}
    assert line_dedup.dedup_lines(no_docs).count() == 0


def test_line_dedup_of_repeated_rows_and_taken_names(spark):
    text = "\none first line\nsecond line\n\nthird line"
    rows = [(1, text, 5, "a"), (1, text, 5, "a"), (1, text, 6, "b"), (2, "zzz\nsecond line\n\nthird line\nend", 7, "c"), (None, "p\nq", 1, "d"), (None, "p\nq", 1, "e"), (3, "q", 0, None), (3, "q", 0, None)]
    out = line_dedup.dedup_lines(spark.createDataFrame(rows, "doc_id bigint, text string, ld_lines int, digest string")).collect()
    got = Counter((r.doc_id, r.text, r._ld_lines, r.ld_removed_lines) for r in out)
    assert got == Counter({(1, text, 5, 0): 1, (1, "", 5, 4): 2, (2, "zzz\nend", 5, 3): 1, (None, "p\nq", 2, 0): 1, (None, "", 2, 2): 1, (3, "q", 1, 0): 2})
    assert sorted(r.ld_lines for r in out) == [0, 0, 1, 1, 5, 5, 6, 7]


def test_lines_whose_digests_clash_stay(spark, monkeypatch):
    rows = [(d, f"{d} own\nshared a\nshared b\n{d} end") for d in range(4)]
    frame = spark.createDataFrame(rows, "doc_id bigint, text string")
    monkeypatch.setattr(line_dedup, "_clashes", lambda rows: spark.createDataFrame([(hashlib.md5(b"shared a").digest(),)], "digest binary"))
    assert {r.doc_id: r.text for r in line_dedup.dedup_lines(frame).collect()} == dict(rows)


def test_embedding_groups_prune_and_large_dimensions(spark, monkeypatch):
    """Many groups: clustered vectors are sent to few of them, and in 512 dimensions nothing is lost either."""
    monkeypatch.setattr(ed, "GROUP_BYTES", 1 << 15)
    rng = np.random.default_rng(3)
    for dims, n_clusters, each in ((32, 30, 40), (512, 8, 30)):
        centres = rng.normal(size=(n_clusters, dims))
        x = (centres[:, None, :] + 0.25 * rng.normal(size=(n_clusters, each, dims))).reshape(-1, dims)
        frame = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id bigint, embedding array<double>").repartition(4)
        sent = []
        real = ed._sending
        monkeypatch.setattr(ed, "_sending", lambda dealt, cosine: sent.append(dealt) or real(dealt, cosine))  # noqa: B023
        got = {r.vec_id: (r.n_links, r.component_id) for r in ed.embedding_near_duplicates(frame).collect()}
        monkeypatch.setattr(ed, "_sending", real)
        unit = x / np.linalg.norm(x, axis=1)[:, None]
        near = unit @ unit.T >= 0.9
        np.fill_diagonal(near, False)
        reach = least_reachable(range(len(x)), [(int(a), int(b)) for a, b in zip(*np.nonzero(near), strict=True)])
        assert got == {i: (int(near[i].sum()), reach[i]) for i in range(len(x))} and near.sum() > len(x)
        dealing = sent[0][dims]
        _, visits = dealing.visits(unit, 0.9)
        assert dealing.n_groups >= 4 and visits.sum() < 0.5 * len(x) * dealing.n_groups
