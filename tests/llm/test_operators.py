"""Operators on small odd tables: nulls, blanks, ties, repeats, clashing columns, empty tables, large groups."""

from collections import Counter, defaultdict
from zlib import crc32

import numpy as np
import pytest

from delprop.llm import ann, decontamination, htmltext, packing, quality, secretscan, sharding, simhash, toxicity, urlfilter
from delprop.llm.common import table
from delprop.llm.queries import QUERIES, URL_RULES, tokenizer_path

DOCS = "doc_id long, text string, lang string, source string, n_chars long, score double, row string, fp long"
BASE = "the quick brown fox jumps over the lazy dog while many other words follow in this rather long sentence about nothing at all"


@pytest.fixture(scope="module")
def odd(spark):
    rows = [(1, BASE), (2, BASE), (3, None), (4, ""), (5, "  \n "), (5, "  \n "), (None, BASE), (None, None), (6, "word " * 20000), (7, 'x token = "0123456789abcdef01234567" y')]
    rows += [(100 + i, f"copy {i % 7} of some shared text that is long enough to matter here") for i in range(60)]
    return spark.createDataFrame([(i, t, "en", None if k % 3 else f"s{k % 4}", None if t is None else len(t), 1.0, "r", 9) for k, (i, t) in enumerate(rows)], DOCS)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


def brute_components(rows):
    fps = [(i, simhash.fingerprint(t)) for i, t in rows]
    parent = list(range(len(fps)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in range(len(fps)):
        for b in range(a):
            if bin(fps[a][1] ^ fps[b][1]).count("1") <= 4:
                parent[find(a)] = find(b)
    least = defaultdict(list)
    for k, (i, _) in enumerate(fps):
        least[find(k)].append(i)
    return Counter((i, min((j for j in least[find(k)] if j is not None), default=None)) for k, (i, _) in enumerate(fps))


def test_shards(odd, none):
    got = sharding.shard(odd, shards=3, ranges_per_shard=8).collect()
    assert len(got) == odd.count() and sharding.shard(none).count() == 0
    for s in {r.shard for r in got}:
        assert sorted(r.slot for r in got if r.shard == s) == list(range(sum(r.shard == s for r in got)))
    want = Counter((r.doc_id, len((r.text or "").encode()) + 16, crc32((r.text or "").encode())) for r in odd.collect())
    assert Counter((r.doc_id, r.size, r.text_crc32) for r in got) == want


def test_shards_are_near_equal(spark, sf):
    docs = table(spark, "/root/testdata/sf0.01", "documents")
    size = Counter()
    for r in sharding.shard(docs, shards=10).collect():
        size[r.shard] += r.size
    assert len(size) == 10 and max(size.values()) < 1.05 * sum(size.values()) / 10


def test_components_equal_brute_force(spark, sf, odd, none):
    got = Counter((r.doc_id, r.component_id) for r in simhash.components(odd).collect())
    assert got == brute_components([(r.doc_id, r.text) for r in odd.collect()])
    docs = table(spark, sf, "documents")
    got = Counter((r.doc_id, r.component_id) for r in simhash.components(docs).collect())
    assert got == brute_components([(r.doc_id, r.text) for r in docs.collect()])
    assert simhash.components(none).count() == 0


def test_large_buckets_go_the_other_way_with_the_same_result(spark, sf):
    docs = table(spark, sf, "documents")
    near = docs.limit(40).selectExpr("doc_id + 10000 as doc_id", "concat(text, ' tail') as text")
    both = docs.select("doc_id", "text").unionByName(near)
    want = Counter((r.doc_id, r.component_id) for r in simhash.components(both).collect())
    got = Counter((r.doc_id, r.component_id) for r in simhash.components(both, bucket_bound=1).collect())
    assert got == want


def test_deduplicate_keeps_one_of_each_group(odd):
    kept = [r.doc_id for r in simhash.deduplicate(odd).collect()]
    groups = brute_components([(r.doc_id, r.text) for r in odd.collect()])
    roots = {c for _, c in groups}
    assert sorted(kept) == sorted(roots) and simhash.deduplicate(odd).columns == odd.columns


def test_deduplicate_tells_rows_without_an_own_id_apart(spark):
    other = ["seven grey herons stood in the shallow river while rain fell over the far northern hills", "a baker in town sells warm rye bread to every early guest before the market opens", "old maps of the coast show three small islands that nobody has ever found again since"]
    # unrelated null ids, a null id that copies an id, an id with two texts of which one copies a smaller id, repeated rows
    rows = [(1, BASE), (None, BASE), (None, other[0]), (None, other[1]), (None, other[1]), (2, BASE), (2, other[2]), (3, "x " * 40), (3, "y " * 40), (3, "y " * 40)]
    docs = spark.createDataFrame([(i, t, k) for k, (i, t) in enumerate(rows)], "doc_id long, text string, fp int")
    got = simhash.deduplicate(docs)
    assert got.columns == docs.columns
    assert Counter((r.doc_id, r.text) for r in got.collect()) == Counter([(1, BASE), (None, other[0]), (None, other[1]), (2, other[2]), (3, "x " * 40), (3, "y " * 40)])


def test_scores_and_filters(spark, odd, none, sf):
    labels = spark.createDataFrame([(1, 1, None), (2, None, 0), (None, 1, 1), (100, 0, 1)], "doc_id long, quality int, toxic int")
    for module, target in ((toxicity, "toxic"), (quality, "quality")):
        model = module.train(odd, labels)
        got = module.score(odd, model).collect()
        assert len(got) == odd.count() and all(0 <= r.score <= 1 and r.predicted in (0, 1) for r in got)
        assert all(r.held_out == (r.doc_id is None or crc32(str(r.doc_id).encode()) % 5 == 0) for r in got)
        assert module.score(none, module.train(none, labels.limit(0))).count() == 0
    assert toxicity.keep_clean(odd, toxicity.train(odd, labels)).columns == odd.columns


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.1"
    labels = {r.doc_id: r for r in table(spark, sf, "labels").collect()}
    for name, target, least in (("op3_toxicity", "toxic", 0.94), ("op10_quality", "quality", 0.97)):
        rows = [r for r in QUERIES[name](spark, sf).collect() if r.held_out and r.doc_id in labels]
        assert np.mean([r.predicted == labels[r.doc_id][target] for r in rows]) > least


def check_pieces(docs, pieces, length=4096):
    code = packing.Encoder(tokenizer_path())
    want = Counter()
    for i, t in docs:
        ids = code.tokenizer.encode(t or "", add_special_tokens=False).ids + [2]
        want[i, len(ids)] += 1
    own, places = defaultdict(list), defaultdict(list)
    for p in pieces:
        own[p.doc_id, p.doc_tokens].append((p.start, p.length))
        places[p.sequence_id].append((p.offset, p.length))
    for key, times in want.items():
        cover = Counter()
        for a, n in own[key]:
            cover.update(range(a, a + n))
        assert set(cover) == set(range(key[1])) and set(cover.values()) == {times}
    assert set(own) == set(want)
    for got in places.values():
        at = 0
        for offset, n in sorted(got):
            assert offset == at
            at += n
        assert at <= length
    assert len(places) == -(-sum(k[1] * n for k, n in want.items()) // length)


def test_packing_round_trip(spark, sf, odd, none):
    check_pieces([(r.doc_id, r.text) for r in odd.collect()], packing.pack(odd, tokenizer_path()).collect())
    docs = table(spark, sf, "documents")
    pieces = packing.pack(docs, tokenizer_path(), targets={"src0": 3.0, "src1": 1.0}).collect()
    check_pieces([(r.doc_id, r.text) for r in docs.collect()], pieces)
    code = packing.Encoder(tokenizer_path())
    texts = {r.doc_id: r.text for r in docs.collect()}
    for p in pieces[::37]:
        ids = np.array(code.tokenizer.encode(texts[p.doc_id], add_special_tokens=False).ids + [2], "<u4")
        assert p.ids_crc32 == crc32(ids[p.start : p.start + p.length].tobytes())
    assert packing.pack(none, tokenizer_path()).count() == 0


def test_packing_keeps_targets_of_many_sources(spark):
    sources = ["big"] * 60 + ["aim"] * 20 + ["gain"] * 20 + [f"rare{k}" for k in range(2000)]
    docs = spark.createDataFrame([(i, "some words of a text " * 20 if i < 100 else "rare words", s) for i, s in enumerate(sources)], "doc_id long, text string, source string")
    pieces = packing.pack(docs, tokenizer_path(), length=256, targets={"aim": 3.0, "gain": 1.0, "absent": 5.0}).collect()
    check_pieces([(r.doc_id, r.text) for r in docs.collect()], pieces, 256)
    assert {p.doc_id: p.queue for p in pieces} == {i: f"s{s}" for i, s in enumerate(sources)}
    first = Counter()
    for p in pieces:
        if p.sequence_id < 4:
            first[p.queue] += p.length
    assert first == {"saim": 768, "sgain": 256}
    everyone = packing.pack(docs, tokenizer_path(), length=256, targets=dict.fromkeys(set(sources), 1.0)).collect()
    check_pieces([(r.doc_id, r.text) for r in docs.collect()], everyone, 256)


def test_url_rules_in_several_files(spark):
    rules = [*URL_RULES, ("block", "a.b.c", "/12"), ("allow", "b.c", "/1234"), ("block", "c", "/123456")]
    pages = spark.createDataFrame([(i, f"http://{h}{p}") for i, (h, p) in enumerate((h, p) for h in ("x.example.com", "a.b.c", "b.c", "q.org", "z.net") for p in ("/en/7", "/es/", "/de/8", "/1234567", "/12"))], "page_id long, url string")
    one, many = ({tuple(r) for r in urlfilter.judge_urls(pages, rules, most=most).collect()} for most in (1 << 30, 64))
    assert one == many and len(urlfilter.parts_of(rules, 64)) > 2
    assert {r[3] for r in one if r[1] == "a.b.c" and r[2] == "/1234567"} == {"a.b.c/12"}  # of three equally long rules the one with the longest host


def test_hot_runs_without_ids_are_cut(spark):
    docs = spark.createDataFrame([(None, BASE) for _ in range(3000)] + [(i, f"text number {i} of the rest") for i in range(300)], "doc_id long, text string")
    size = Counter()
    for r in sharding.shard(docs, shards=6).collect():
        size[r.shard] += r.size
    assert len(size) == 6 and max(size.values()) < 1.1 * sum(size.values()) / 6


def test_equal_texts_stay_together_while_they_fit(spark):
    docs = spark.createDataFrame([(i, f"group {i % 97} " * 9) for i in range(4000)], "doc_id long, text string")
    where = defaultdict(set)
    for r in sharding.shard(docs, shards=7, ranges_per_shard=4).collect():
        where[r.text_crc32].add(r.shard)
    assert all(len(s) == 1 for s in where.values())


def test_search_finds_rows_that_share_an_id(spark):
    rows = [(20, [1.0, 0.0]), (1, [0.9, 0.1]), (1, [0.1, 0.9]), (20, [0.5, 0.5])]
    got = ann.search(spark.createDataFrame(rows, "vec_id long, embedding array<float>")).collect()
    assert sorted((r.query_id, r.vec_id, round(r.score, 3)) for r in got) == [(20, 1, 0.1), (20, 1, 0.5), (20, 1, 0.5), (20, 1, 0.9), (20, 20, 0.5), (20, 20, 0.5)]


def test_search_recall_at_production_depth(spark):
    rows = {r.vec_id: np.array(r.embedding, float) for r in table(spark, "/root/testdata/sf0.1", "embeddings").collect()}
    ids = np.array(sorted(rows))
    x = np.array([rows[i] for i in ids])
    got = defaultdict(set)
    for r in ann.search(table(spark, "/root/testdata/sf0.1", "embeddings"), least_blocks=1, depth=400).collect():
        got[r.query_id].add(r.vec_id)
    hits = total = 0
    for q in ids[ids % 20 == 0]:
        score = np.where(ids == q, -np.inf, x @ rows[q])
        hits += len(got[q] & set(ids[np.argsort(-score)[:20]].tolist()))
        total += 20
    assert len(ids) == 2000 and hits / total >= 0.95


def test_toxic_recall_by_language(spark):
    sf = "/root/testdata/sf0.1"
    marks = {r.doc_id: r.toxic for r in table(spark, sf, "labels").collect()}
    lang = {r.doc_id: r.lang for r in table(spark, sf, "documents").select("doc_id", "lang").collect()}
    rows = [r for r in QUERIES["op3_toxicity"](spark, sf).collect() if r.held_out and marks.get(r.doc_id) is not None]
    toxic = [r for r in rows if marks[r.doc_id] == 1]
    assert np.mean([r.predicted for r in toxic]) >= 0.85
    assert np.mean([r.predicted for r in toxic if lang[r.doc_id] != "en"]) >= 0.75
    assert np.mean([1 - r.predicted for r in rows if marks[r.doc_id] == 0]) >= 0.99


def test_urls(spark):
    rows = [(1, "http://A.Example.COM/en/7?x"), (2, None), (3, "no scheme/en/"), (4, "https://x.org/es/a#b"), (4, "https://x.org/es/a#b"), (5, "a://b://c/en/"), (6, "http://com?/en/")]
    pages = spark.createDataFrame([(i, u, "h") for i, u in rows], "page_id long, url string, host string")
    got = Counter(tuple(r) for r in urlfilter.judge_urls(pages, URL_RULES).collect())
    assert got[1, "a.example.com", "/en/7", "example.com/en/7", "allow"] == 1 and got[2, "", "", None, "allow"] == 1 and got[3, "", "", None, "allow"] == 1
    assert got[4, "x.org", "/es/a", "org/es/", "block"] == 2 and got[5, "b:", "//c/en/", None, "allow"] == 1 and got[6, "com", "", None, "allow"] == 1
    assert urlfilter.judge_urls(pages.limit(0), URL_RULES).count() == 0


def test_secrets(odd, none):
    chain = secretscan.train(odd)
    got = {r.doc_id: r for r in secretscan.scan(odd, chain).collect()}
    assert (got[7].n_assign, got[7].n_hex) == (1, 1) and got[4].spans == "" and len(got[7].spans.split(",")) == 2
    clean = secretscan.redact(odd, chain)
    assert clean.columns == odd.columns and clean.count() == odd.count()
    text = {r.doc_id: r.text for r in clean.collect()}
    assert "0123456789abcdef" not in text[7] and text[1] == BASE
    assert secretscan.scan(none, secretscan.train(none)).count() == 0


def test_search_recall_and_bad_vectors(spark):
    sf = "/root/testdata/sf0.01"
    found = ann.search(table(spark, sf, "embeddings"), depth=60).collect()
    rows = {r.vec_id: np.array(r.embedding, float) for r in table(spark, sf, "embeddings").collect()}
    hits = total = 0
    for q in [i for i in rows if i % 20 == 0]:
        exact = sorted(((-float((rows[q] * v).sum()), i) for i, v in rows.items() if i != q))[:20]
        mine = [r.vec_id for r in sorted(found, key=lambda r: r["rank"]) if r.query_id == q]
        hits, total = hits + len({i for _, i in exact} & set(mine)), total + 20
        assert len(mine) == 20
    assert hits / total > 0.95
    bad = [(0, [1.0, 0.0]), (20, [1.0, 0.0]), (1, None), (2, [0.0, 0.0]), (3, [float("nan"), 1.0]), (4, [None, 1.0]), (5, [float("inf"), 1.0]), (6, [1.0, 0.0]), (7, [1.0]), (None, [1.0, 1.0]), (6, [1.0, 0.0])]
    got = ann.search(spark.createDataFrame([(i, v, 0.0) for i, v in bad], "vec_id long, embedding array<float>, score double")).collect()
    assert sorted((r.query_id, r["rank"], r.vec_id, r.score) for r in got) == [(0, 1, 6, 1.0), (0, 2, 6, 1.0), (0, 3, 20, 1.0), (20, 1, 0, 1.0), (20, 2, 6, 1.0), (20, 3, 6, 1.0)]
    assert ann.search(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


def test_leaks_equal_brute_force(spark, odd, none):
    sf = "/root/testdata/sf0.01"
    docs, items = table(spark, sf, "documents"), table(spark, sf, "benchmark")
    got = {(r.doc_id, r.item_id) for r in decontamination.contaminated(docs, items).collect()}
    plain = lambda t: " ".join((t or "").split())
    want = {(d.doc_id, b.item_id) for b in items.collect() for d in docs.collect() if plain(b.text) in plain(d.text)}
    assert want <= got and len(got - want) <= 0.1 * len(want)
    kept = {r.doc_id for r in decontamination.keep_clean(docs, items).collect()}
    assert kept == {r.doc_id for r in docs.collect()} - {d for d, _ in got}
    assert decontamination.contaminated(odd, items, block_windows=50).count() == 0 and decontamination.contaminated(none, items).count() == 0
    assert decontamination.contaminated(docs, items.limit(0)).count() == 0


def test_pages(spark):
    pages = spark.createDataFrame([(1, "u", None, "x"), (None, None, "<article><p>a b.</p></article>", "x"), (2, "u", "", "x")], "page_id long, url string, html string, text string")
    assert [r.n_chars for r in htmltext.extract(pages).collect()] == [0, 4, 0]
    assert htmltext.extract(pages.limit(0)).count() == 0


def test_pipeline_stages_on_the_small_tables(spark, sf):
    import corpus_pipeline

    docs = table(spark, sf, "documents")
    seen = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, seen, sf)
        assert out.columns == docs.columns, name
        seen = spark.createDataFrame(out.collect(), docs.schema)
        assert seen.count() > 0.5 * docs.count()
    pieces = corpus_pipeline.STAGES[-1][1](spark, seen, sf).collect()
    check_pieces([(r.doc_id, r.text) for r in seen.collect()], pieces)


def test_search_gives_the_same_for_single_and_double_precision(spark):
    rows = [(i, [float(np.float32(np.sin(i * (j + 1)))) for j in range(4)]) for i in range(60)] + [(60, None), (61, [0.0] * 4), (62, [float("nan"), 1.0, 1.0, 1.0])]
    single = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    double = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    found = [sorted(map(tuple, ann.search(t, k=5, least_blocks=2).collect())) for t in (single, double)]
    assert found[0] == found[1] and {r[0] for r in found[0]} == {20, 40} and len(found[0]) == 2 * 5  # the vector of id 0 is zero
