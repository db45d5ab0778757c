"""Odd rows and sizes: exact scores of any size, spills, bounds between buckets, long texts, repeated rows, clashing names."""

import collections
import itertools
import math
import random

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from cubecast.llm import buckets, exact_dedup, jaccard_join, mixing, pieces, quality, repeats, substring_dedup, suffix_dedup, tables, token_counts, topk_search, url_rules
from cubecast.llm.arrays import buffer_of
from cubecast.llm.queries import COUNTED_WITH, ENCODED_WITH

from . import brute

DOCS = "doc_id long, text string, source string"


def frame(spark, rows, extra=()):
    out = spark.createDataFrame([(d, t, "s") for d, t in rows], DOCS)
    for name in extra:
        out = out.withColumn(name, F.lit("clash"))
    return out


def ranked(vectors, k=5):
    """query, rank, candidate, true score."""
    whole = [(i, [math.floor(64 * x) if abs(x) < 2**50 else int(x) * 64 for x in e]) for i, e in vectors if e is not None and all(x is not None and math.isfinite(x) for x in e)]
    out = set()
    for q, x in whole:
        if q is not None and q % 20 == 0:
            best = sorted((-sum(a * b for a, b in zip(x, y, strict=False)), brute.ident(j), j) for j, y in whole if j != q)[:k]
            out |= {(q, r + 1, j, -s) for r, (s, _, j) in enumerate(best)}
    return out


@pytest.mark.parametrize("size", [1e3, 1e7, 1e8, 1e10, 1e30, 1e200])
def test_top_k_scores_are_exact_at_any_size(spark, size):
    r = random.Random(int(math.log10(size)))
    vectors = [(i, [r.choice((1.0, -1.0)) * r.random() * r.choice((1.0, size)) for _ in range(3)]) for i in range(90)] + [(20, [size, 1.0]), (200, None), (220, [1.0, float("nan")])]
    vectors = [v for i, v in enumerate(vectors) if i != 20]
    table = spark.createDataFrame(vectors, "vec_id long, embedding array<double>")
    for shard in (16, 10**6):
        got = {tuple(x) for x in topk_search.top_k(table, F.col("id") % 20 == 0, k=5, shard_rows=shard).select("query_id", "rank", "vec_id", "score").collect()}
        most = 2**63 - 1
        assert got == {(q, n, v, min(max(s, -most), most)) for q, n, v, s in ranked(vectors)}


def test_top_k_of_the_judged_cases(spark):
    table = spark.createDataFrame([(20, [1e8, 1.0]), (1, [1.0, 1.0]), (3, [1e8, 0.25]), (40, [2.0**23 + 1, 2.0**23]), (5, [2.0**23 + 1, 1.0])], "vec_id long, embedding array<double>")
    got = {(x.query_id, x.rank): (x.vec_id, x.score) for x in topk_search.top_k(table, F.col("id") % 20 == 0, k=4).collect()}
    assert got[20, 1][0] == 3 and got[20, 1][1] == 2**63 - 1
    whole = lambda e: [math.floor(64 * x) for x in e]
    assert got[40, 2] == (5, 64 * 64 * ((2**23 + 1) ** 2 + 2**23)) or got[40, 1] == (20, sum(a * b for a, b in zip(whole([2.0**23 + 1, 2.0**23]), whole([1e8, 1.0]), strict=True)))


def test_urls_with_line_feeds(spark):
    urls = [(1, "http://a\nb.example.com/en/7"), (2, "http://\nfoo.com/en/z"), (3, "http://example.com\n/en/7"), (4, "http://x.org#y/es/"), (5, "http://COM/en/")]
    rules = url_rules.RULES
    got = {r.page_id: (r.rule, r.verdict) for r in url_rules.judged(spark.createDataFrame(urls, "page_id long, url string"), rules).collect()}
    assert got == {1: ("example.com/en/7", "allow"), 2: ("com/en/", "block"), 3: (None, "allow"), 4: (None, "allow"), 5: ("com/en/", "block")}


def test_trie_spills_below_a_long_shared_prefix():
    head = b"x" * 2000
    pairs = [(head + str(i % 200).encode(), (1, i, 1)) for i in range(300)] + [(head[:n], (1, 1000 + n, 1)) for n in range(0, 2000, 100)]
    want = collections.Counter(k for k, _ in pairs)
    for bound in (2000, 20_000, 10**8):
        got = {k: n for k, (_, _, n) in exact_dedup.owners_of(iter(pairs), bound)}
        assert got == want


def test_dedup_stages_act_on_rows(spark):
    long = " ".join(f"w{i}" for i in range(60))
    rows = [(None, "same text"), (None, "same text"), (1, "same  text"), (1, "same  text"), (2, "other"), (2, "another"), (None, None), (None, ""), (3, long), (4, long + " x"), (3, long), (None, long)]
    names = ("row_key", "__gone", "root", "doc", "key", "times", "__times", "size", "gone")
    docs = frame(spark, rows, names)
    exact = exact_dedup.deduplicate(docs)
    assert exact.columns == docs.columns
    assert sorted(((r.doc_id or 0, r.text or "") for r in exact.collect())) == [(0, ""), (1, "same  text"), (2, "another"), (2, "other"), (3, long), (4, long + " x")]
    near = jaccard_join.distinct_documents(docs)
    assert near.columns == docs.columns
    kept = collections.Counter((r.doc_id or 0, r.text or "") for r in near.collect())
    assert kept == collections.Counter({(1, "same  text"): 1, (2, "another"): 1, (2, "other"): 1, (3, long): 1, (0, ""): 2})
    mixed = mixing.mixed_documents(docs)
    assert mixed.columns == docs.columns
    plan = mixing.mix(docs).collect()
    assert mixed.where("text is not null and text <> ''").count() == sum(r.taken // r.size for r in plan if r["size"])
    none = spark.createDataFrame([], DOCS)
    assert exact_dedup.deduplicate(none).count() == jaccard_join.distinct_documents(none).count() == mixing.mixed_documents(none).count() == 0


def plain_judgement(rows):
    """What is whole, and what is to be checked, by key and content."""
    classes = collections.defaultdict(lambda: collections.defaultdict(list))
    for i, r in enumerate(rows):
        classes[r[:2]][r[2]].append((r[3], i))
    whole, check = set(), set()
    for by in classes.values():
        for members in by.values():
            least = min(members)[0]
            whole |= {i for d, i in members if d > least}
            if len(by) > 1:
                check |= {i for d, i in members if d == least}
    return whole, check


@pytest.mark.parametrize(("seed", "rows", "n"), [(1, 40, 7), (2, 10**6, 5), (3, 25, 1), (4, 60, 30)])
def test_buckets_spill_and_compare_across_bounds(tmp_path, seed, rows, n):
    r = np.random.default_rng(seed)
    size = 3000
    table = {"lead": r.integers(-3, 3, size) * (2**60), "gram": r.integers(0, 3, size), "digest": r.integers(0, 4, size), "doc": r.integers(0, 50, size), "place": np.arange(size)}
    table["doc"][table["lead"] == 0] = 7  # one path again and again in one document
    table = {k: v.astype(np.int64) for k, v in table.items()}
    table["src"], table["dst"] = table["place"].copy(), table["place"].copy()
    cut = buckets.picked(buckets.ordered(table), n)
    where = buckets.places(cut, table)
    whole, check, notes, pending, sources = set(), set(), [], [], collections.defaultdict(set)
    for b in range(n):
        mine = buckets.taken(table, where == b)
        judge = buckets.Judge(b, True, True)
        parts = [buckets.taken(mine, slice(i, i + 10)) for i in range(0, len(mine["doc"]), 10)]
        out = [x for block in buckets.in_order(iter(parts), rows, str(tmp_path)) for x in judge(block)] + list(judge.end())
        for row in itertools.chain.from_iterable(x.to_pylist() for x in out):
            if row["kind"] == buckets.SUMMARY:
                notes.append((b, row["note"]))
            elif row["kind"] == buckets.SOURCE:
                sources[row["id"]].add(row["doc"])
            elif row["kind"] in (buckets.WHOLE, buckets.CHECK):
                (whole if row["kind"] == buckets.WHOLE else check).add(row["place"])
            else:
                pending.append((b, row))
    facts = {b: x for b, *x in buckets.compared(notes)}
    for b, row in pending:
        carry, first_many, last_many = facts[b]
        if row["kind"] == buckets.FIRST and carry is not None and row["doc"] > carry:
            whole.add(row["place"])
        elif first_many if row["kind"] == buckets.FIRST else last_many:
            check.add(row["place"])
    want = plain_judgement(list(zip(*(table[c].tolist() for c in buckets.ORDER), strict=True)))
    assert (whole, check) == want
    repeated = {k for k, docs in collections.Counter((a, b, c) for a, b, c, _ in {tuple(x) for x in zip(*(table[c].tolist() for c in buckets.ORDER), strict=True)}).items() if docs > 1}
    assert len(sources) >= len(repeated)


def test_quicksort_orders_by_all_columns():
    r = np.random.default_rng(5)
    columns = [r.integers(0, 3, 50_000), r.integers(0, 50, 50_000), r.integers(-(2**62), 2**62, 50_000)]
    got = buckets.quicksort(columns)
    assert np.array_equal(np.stack([c[got] for c in columns]), np.stack([c[np.lexsort(columns[::-1])] for c in columns]))


def test_long_texts_in_parts(spark, monkeypatch):
    r = random.Random(6)
    words = ["".join(r.choice("abcdeé ") for _ in range(r.randint(1, 9))) for _ in range(4000)]
    text = " ".join(r.choice(words) for _ in range(9000))
    rows = [(1, text), (2, text[5000:40_000] + "!" + text[:300]), (3, "q" * 9000), (4, None)]
    monkeypatch.setattr(repeats, "LONG_PART", 7001)
    want = brute.repeated_bytes(rows)
    local = [x for b in path_batches(rows) for x in b]
    assert len(local) > 0
    assert sorted(tuple(brute.ident(v) if i == 0 else v for i, v in enumerate(x)) for x in suffix_dedup.repeated_bytes(frame(spark, rows)).collect()) == want
    model = pieces.Model.load(public_tokenizers.path(ENCODED_WITH))
    import pyarrow as pa

    monkeypatch.setattr(pieces, "SLICE", 1000)
    whole, _ = model.encode_some(pa.array([text]), True)
    parts, cuts = model.encode(pa.array([text]))
    assert np.array_equal(whole, parts) and cuts.tolist() == [0, len(whole)]


def test_pieces_are_found_without_a_search_for_each_substring(monkeypatch):
    import sentencepiece

    path, r, searched, search = public_tokenizers.path(ENCODED_WITH), random.Random(8), [], np.searchsorted
    text = " ".join("".join(r.choice("etaoinshrdlué") for _ in range(r.randint(1, 12))) for _ in range(5000))
    model = pieces.Model.load(path)
    monkeypatch.setattr(pieces, "MEMORIES", {})
    monkeypatch.setattr(np, "searchsorted", lambda a, v, *x, **y: searched.append(np.size(v)) or search(a, v, *x, **y))
    ids, _ = model.encode(pa.array([text]))
    assert ids.tolist() == sentencepiece.SentencePieceProcessor(model_file=path).encode(text)
    assert sum(searched) < 3 * len(text)


def test_remembered_pairs(monkeypatch):
    monkeypatch.setattr(pieces, "REMEMBERED", 70_000)
    r, known, told = np.random.default_rng(9), pieces.Memory(), {}
    for _ in range(30):
        pairs = r.integers(0, 2**41, 5000)
        pairs[::2] = pairs[0] + np.arange(2500) * 2**r.integers(0, 9)  # many that are alike
        pairs = np.unique(pairs)
        assert np.array_equal(known.find(pairs), [told.get(x, -1) for x in pairs.tolist()])
        pairs = pairs[known.find(pairs) < 0]
        if known.count + len(pairs) > 70_000:
            told = {}
        told |= dict(zip(pairs.tolist(), (pairs % 3 == 0).tolist(), strict=True))
        known.add(pairs, pairs % 3 == 0)
        every = np.array(list(told))
        assert known.count == len(told) <= 70_000 and 2 * known.count <= len(known.slots) and np.array_equal(known.find(every), list(told.values()))


def path_batches(rows):
    """Paths of a long text read in parts hold every window once."""
    from cubecast.llm.arrays import buffer_of
    import pyarrow as pa

    buf, offsets = buffer_of(pa.array([rows[0][1]]))
    found = []
    for base, part, cut in repeats.parts_of(suffix_dedup.Suffixes, buf, offsets):
        at, row = repeats.all_windows(cut, 50)
        found += (at + base).tolist()
    assert found == list(range(int(offsets[-1]) - 49))
    yield found


def test_texts_of_millions_of_bytes(spark):
    text = "alpha beta " * 300_000
    rows = [(1, text), (2, "alpha beta " * 40), (3, "z" * 200_000)]
    docs = frame(spark, rows)
    counts = {r.doc_id: r.n_tokens for r in token_counts.count_tokens(docs, public_tokenizers.path(COUNTED_WITH)).collect()}
    assert counts[1] == 300_000 * counts[2] // 40
    assert {r.doc_id: r.n_shingles for r in jaccard_join.linked_documents(docs).collect()}[1] == 2
    gone = {r.doc_id: (r.n_words, r.n_removed) for r in substring_dedup.repeated_words(docs).collect()}
    assert gone[1] == (600_000, 0) and gone[2] == (80, 80)
    assert {r.doc_id: r.n_removed for r in suffix_dedup.repeated_bytes(docs).collect()}[2] == 11 * 40
    assert {r.doc_id: r.exact for r in pieces.round_trip(docs, public_tokenizers.path(ENCODED_WITH)).collect()} == {1: True, 2: True, 3: True}
    assert exact_dedup.duplicate_classes(docs).count() == 3
    scorer, _ = quality.trained(docs)
    assert quality.judged(docs, scorer).count() == 3


def plain_em(patterns, counts, rounds=100):
    """The same estimate, pattern by pattern and labeller by labeller."""
    post = []
    for p in patterns:
        good, bad = sum(v == 1 for v in p), sum(v == 2 for v in p)
        x = (good + 0.5) / (good + bad + 1.0) if good + bad else 0.5
        post.append(min(x, 0.5) if bad else x)
    for _ in range(rounds):
        table = []
        for c in (0, 1):
            share = [x if c == 0 else 1 - x for x in post]
            rows = []
            for j in range(len(patterns[0])):
                mass = [1.0 + sum(n * s for p, n, s in zip(patterns, counts, share, strict=True) if p[j] == v) for v in range(3)]
                rows.append([m / sum(mass) for m in mass])
            table.append(rows)
        for j in range(len(patterns[0])):
            table[0][j][2] = min(table[0][j][2], table[1][j][2] / quality.EDGE)
            table[1][j][1] = min(table[1][j][1], table[0][j][1])
        prior = (sum(n * x for n, x in zip(counts, post, strict=True)) + 1) / (sum(counts) + 2)
        new = []
        for p in patterns:
            a = math.log(prior) + sum(math.log(table[0][j][v]) for j, v in enumerate(p))
            b = math.log(1 - prior) + sum(math.log(table[1][j][v]) for j, v in enumerate(p))
            new.append(1 / (1 + math.exp(min(max(b - a, -50), 50))))
        done = max(abs(x - y) for x, y in zip(new, post, strict=True)) < 1e-9
        post = new
        if done:
            break
    return post, prior


def test_estimates_equal_plain_expectation_maximisation():
    r = random.Random(8)
    patterns = sorted({tuple(r.choice((0, 0, 1, 2)) for _ in range(4)) for _ in range(40)})
    counts = [r.randint(1, 50) for _ in patterns]
    post, _, prior = quality.estimated(np.array(patterns), np.array(counts, float))
    want, p = plain_em(patterns, counts)
    assert post == pytest.approx(want, abs=1e-6) and prior == pytest.approx(p, abs=1e-6)


def test_scores_equal_a_plain_scorer(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    scorer, _ = quality.trained(docs)
    rows = {r.doc_id: r.score for r in quality.judged(docs, scorer).collect()}
    import pyarrow as pa

    for d in docs.limit(15).collect():
        reader = quality.Reader(pa.array([d.text]))
        total = scorer.bias + sum(float(scorer.weights[f]) for features in reader.features() for f in features) / (int(reader.count[0]) + quality.CALM)
        want = 1 / (1 + math.exp(-min(max(total, -30), 30))) if reader.count[0] else 0.0
        assert rows[d.doc_id] == pytest.approx(want, abs=1e-5)


def test_stages_equal_plain_versions(spark, sf):
    """Each stage of the pipeline on what the one before kept."""
    import corpus_pipeline
    import sentencepiece

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    scorer, _ = quality.trained(docs)
    good = {r.doc_id for r in quality.judged(docs, scorer).where("kept").collect()}
    now = stages["quality_classifier"](spark, docs, sf)
    assert {r.doc_id for r in now.collect()} == good
    kept = spark.createDataFrame(now.collect(), docs.schema)
    rows = [(r.doc_id, r.text) for r in kept.collect()]
    now = stages["exact_dedup"](spark, kept, sf)
    assert {r.doc_id for r in now.collect()} == {d for d, keep, *_ in brute.exact(rows) if d == keep}
    kept = spark.createDataFrame(now.collect(), docs.schema)
    rows = [(r.doc_id, r.text) for r in kept.collect()]
    now = stages["ngram_jaccard_join"](spark, kept, sf)
    assert {r.doc_id for r in now.collect()} == {d for d, n, c in brute.linked(rows, 5, 80) if d == c or not n}
    kept = spark.createDataFrame(now.collect(), docs.schema)
    plan = {r.doc_id: r.taken // r.size if r["size"] else 1 for r in mixing.mix(kept).collect()}
    now = stages["source_mixing"](spark, kept, sf)
    assert collections.Counter(r.doc_id for r in now.collect()) == collections.Counter({d: n for d, n in plan.items() if n})
    kept = spark.createDataFrame(now.collect(), docs.schema)
    library = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path(ENCODED_WITH))
    got = sorted((r.doc_id, r.ids) for r in stages["piece_encoding"](spark, kept, sf).collect())
    assert got == sorted((r.doc_id, library.encode(r.text or "")) for r in kept.collect())


def test_shared_folder_is_refused_only_on_a_cluster(spark):
    assert tables.shared_folder(spark)
    table = tables.shared_table(spark.range(5))
    assert table.count() == 5
    tables.forget(table)


def test_shingles_are_counted_in_all_documents(spark):
    texts = [f"a{i} b{i} c{i} d{i}" + (f" p{i % 20} q r s{i % 20}" if i < 480 else f" t{i % 1000} u v w{i % 1000}") for i in range(9000)]
    frame = spark.createDataFrame(list(enumerate(texts)), "doc long, text string").repartition(3, "doc")
    passages = [f"p{i} q r s{i}" for i in range(20)] + [f"t{i} u v w{i}" for i in range(1000)]
    want, rare = np.split(np.array([jaccard_join.shingles(*buffer_of(pa.array([p])), 4)[0][0] for p in passages]), [20])
    got = set(jaccard_join.frequent_shingles(frame, 4).tolist())
    assert set(want.tolist()) <= got and not got & set(rare.tolist())


def test_most_counts_go_where_too_many_are_held(monkeypatch):
    monkeypatch.setattr(jaccard_join, "HELD", 100)
    heavy = jaccard_join.Heavy()
    for i in range(400):
        value = np.sort(np.array([7, *range(1000 + 20 * i, 1020 + 20 * i)], np.uint64))
        heavy.add(value, np.array([0, len(value)]), np.array([i]))
    key, count = heavy.found()
    assert heavy.sets == 400 and key.tolist() == [7] and count.tolist() == [400] and len(heavy.key) <= 100


def test_training_rows_are_sparse(spark, sf):
    dense = np.zeros((5, 3 << 11), np.float16)
    dense[0, [1, 6000]], dense[2, [1, 2, 3]], dense[4, 5] = (0.5, 0.25), (0.1, 0.2, 0.3), 1
    rows = [np.flatnonzero(r).astype("<u2").tobytes() + r[np.flatnonzero(r)].astype("<f2").tobytes() for r in dense]
    x, w, g = quality.Shares(rows, dense.shape[1]), np.random.default_rng(1).random(dense.shape[1], np.float32), np.arange(5, dtype=np.float32)
    assert np.allclose(x.times(w), dense.astype(np.float32) @ w) and np.allclose(x.turned(g), dense.astype(np.float32).T @ g)
    empty = quality.Shares([b"", b""], 8)
    assert not empty.times(np.ones(8, np.float32)).any() and not empty.turned(np.ones(2, np.float32)).any()


def test_rules_are_those_of_the_contract(spark):
    listed = "block com/en/, allow example.com/en/7, allow net/de/, block example.net/de/8, block org/es/"
    assert [f"{r[0]} {url_rules.name_of(r)}" for r in url_rules.RULES] == listed.split(", ")
    urls = spark.createDataFrame([(1, "http://a.net/de/1"), (2, "http://www.example.net/de/81"), (3, "http://example.net/de/7")], "page_id long, url string")
    assert {r.page_id: (r.rule, r.verdict) for r in url_rules.judged(urls, url_rules.RULES).collect()} == {1: ("net/de/", "allow"), 2: ("example.net/de/8", "block"), 3: ("net/de/", "allow")}
    assert "('allow', 'net', '/de/', 2)" in url_rules.oracle()


def test_search_of_whole_numbers_takes_one_product_a_leaf(monkeypatch):
    import numpy as np

    from cubecast.llm import topk_search

    rng = np.random.default_rng(5)
    points, ids, k = rng.integers(-3, 4, (1500, 6)).astype(float), rng.permutation(1500), 20
    own = np.arange(0, 1500, 5)
    queries = points[np.argsort(ids)][own]
    want = {}
    for q, vec in zip(own, queries, strict=True):
        want[int(q)] = sorted((-int(s), int(i)) for s, i in zip(points @ vec, ids, strict=True) if i != q)[:k]
    monkeypatch.setattr(topk_search, "exact_scores", None)
    for reach in (None, 5):  # without a level, and with that of the tenth best
        level = np.full(len(own), -(2**63) if reach is None else 0, np.int64)
        limit = np.full(len(own), 2**63 - 1, np.int64)
        if reach:
            level, limit = (np.array([f * want[int(q)][9][j] for q in own]) for j, f in ((0, -1), (1, 1)))
        best = topk_search.search(topk_search.BallTree(points), ids, queries, own, k, level, limit, None, None)
        got = {int(q): [] for q in own}
        for r, s, i in zip(best.row, best.score, best.ident, strict=True):
            got[int(own[r])].append((-int(s), int(i)))
        assert got == {q: w[: 10 if reach else k] for q, w in want.items()}
