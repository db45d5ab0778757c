"""Corpus operators against brute force, libraries, round trips and labels; edge cases of every operator."""

import collections
import random

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from cubecast.llm import components, exact_dedup, jaccard_join, mixing, pieces, quality, substring_dedup, suffix_dedup, token_counts, topk_search, url_rules
from cubecast.llm.queries import COUNTED_WITH, ENCODED_WITH

from . import brute

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
ODD = [(None, "x" * 300), (900, "x" * 300), (901, None), (902, ""), (903, "a b " * 700), (904, "a b " * 699), (904, "a b " * 699), (905, " \t\n"), (906, "Short one"), (907, "short  ONE"), (908, "😀 ñ ▁ é " * 30), (909, "a\u0000b")]


@pytest.fixture(scope="module")
def texts(spark, sf):
    given = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").limit(60).collect()]
    return given + ODD + [(950 + i, given[i][1][: 400 + 10 * i]) for i in range(5)]


def frame(spark, rows):
    """Rows as documents, with a column whose name clashes with the operators' own."""
    return spark.createDataFrame([(d, t, "en", f"s{(d or 0) % 3}", len(t or "")) for d, t in rows], SCHEMA).withColumn("key", F.lit(1)).withColumn("size", F.lit("x")).repartition(3)


def got(df):
    return sorted(tuple(brute.ident(x) if i == 0 or n in ("keep_id", "component_id") else x for i, (n, x) in enumerate(zip(df.columns, r, strict=True))) for r in df.collect())


def test_repeated_words(spark, texts):
    assert got(substring_dedup.repeated_words(frame(spark, texts))) == brute.repeated_words(texts)


def test_repeated_bytes(spark, texts):
    assert got(suffix_dedup.repeated_bytes(frame(spark, texts))) == brute.repeated_bytes(texts)


def test_exact_duplicates_and_their_removal(spark, texts):
    docs = frame(spark, texts)
    assert got(exact_dedup.duplicate_classes(docs)) == brute.exact(texts)
    kept = exact_dedup.deduplicate(docs)
    assert kept.columns == docs.columns and kept.where("doc_id = 907").count() + kept.where("doc_id = 906").count() == 2


def test_trie_spills_by_subtree():
    r = random.Random(1)
    keys = [bytes(r.choice(b"abc") for _ in range(r.randint(0, 9))) for _ in range(3000)]
    pairs = [(k, (len(k), i, 1)) for i, k in enumerate(keys)]
    want = collections.Counter(keys)
    for bound in (10**9, 200):
        found = {k: (owner, n) for k, (_, owner, n) in exact_dedup.owners_of(iter(pairs), bound)}
        assert {k: n for k, (_, n) in found.items()} == want
        assert all(keys.index(k) == owner for k, (owner, _) in found.items())


def perturbed(seed):
    r = random.Random(seed)
    rows = []
    for _ in range(25):
        base = [r.choice("abcdefgh") * r.randint(1, 3) for _ in range(r.choice([1, 2, 3, 4, 5, 6, 8, 11, 20, 60, 200]))]
        for _ in range(r.choice([1, 3, 20])):
            w = list(base)
            for _ in range(r.randint(0, max(1, len(w) // 25))):
                i = r.randrange(len(w))
                w[i] = r.choice("XYZ") * 2
            rows.append((len(rows) * 7919 % 100003, " ".join(w)))
    chain = [str(i) for i in range(120)]
    for k in range(330):  # one region of more than a tile
        w = list(chain)
        for _ in range(r.randint(0, 6)):
            w[r.randrange(120)] = f"z{r.randrange(4)}"
        rows.append((10**6 + k, " ".join(w)))
    return rows


@pytest.mark.parametrize(("size", "percent"), [(4, 85), (5, 80)])
def test_jaccard_components(spark, texts, size, percent):
    rows = texts + perturbed(size)
    assert got(jaccard_join.linked_documents(frame(spark, rows), size=size, percent=percent)) == brute.linked(rows, size, percent)


def test_signatures_meet_for_every_linked_pair():
    r = np.random.default_rng(4)
    frequent = np.sort(r.integers(0, 2**63, 40).astype(np.uint64))
    for percent in (80, 85, 90):
        for _ in range(150):
            n = int(r.integers(1, 120))
            x = np.concatenate([r.integers(0, 2**64, n, dtype=np.uint64), frequent[: r.integers(0, 30)]])
            y = x[r.random(len(x)) > r.random() * 0.2]
            y = np.concatenate([y, r.integers(0, 2**64, int(r.integers(0, 1 + n // 12)), dtype=np.uint64)])
            x, y = np.unique(x), np.unique(y)
            if not len(y):
                continue
            both = len(np.intersect1d(x, y))
            if 100 * both >= percent * (len(x) + len(y) - both):
                row, key = jaccard_join.signatures(np.concatenate([x, y]), np.array([0, len(x), len(x) + len(y)]), percent, frequent)
                assert set(key[row == 0]) & set(key[row == 1])


def test_components(spark):
    r = random.Random(2)
    edges = [(r.randrange(400), r.randrange(400)) for _ in range(250)] + [(i, i + 1) for i in range(1000, 1040)] + [(5, 5)]
    root = list(range(2000))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    nodes = {x for e in edges if e[0] != e[1] for x in e}
    out = components.components(spark.createDataFrame(edges, "a long, b long"))
    assert {tuple(x) for x in out.collect()} == {(x, find(x)) for x in nodes}


def test_token_counts(spark, texts):
    from tokenizers import Tokenizer

    path = public_tokenizers.path(COUNTED_WITH)
    rows = texts + [(980, "<|endoftext|> it's 12 a<|startoftext|>b ÀÉ x́"), (981, "q" * 5000)]
    t = Tokenizer.from_file(path)
    want = sorted((brute.ident(d), len((x or "").encode()), len(t.encode(x or "", add_special_tokens=False)), len(t.encode(x or "", add_special_tokens=False)) > 2048) for d, x in rows)
    assert got(token_counts.count_tokens(frame(spark, rows), path)) == want


def test_pieces_equal_the_library_and_round_trip(spark, texts):
    import sentencepiece

    path = public_tokenizers.path(ENCODED_WITH)
    lib = sentencepiece.SentencePieceProcessor(model_file=path)
    r = random.Random(7)
    rows = texts + [(1000 + i, "".join(r.choice("abcdeéß日 \n.😀  ") for _ in range(r.randint(0, 120)))) for i in range(100)] + [(1200, "ab" * 900), (1201, "  lead  and trail  ")]
    out = pieces.encoded(frame(spark, rows), path)
    assert sorted((brute.ident(x.doc_id), x.ids) for x in out.collect()) == sorted((brute.ident(d), lib.encode(t or "")) for d, t in rows)
    back = pieces.decoded(out, path)
    assert sorted((brute.ident(x.doc_id), x.text) for x in back.collect()) == sorted((brute.ident(d), (t or "").replace("▁", " ")) for d, t in rows)
    assert pieces.round_trip(frame(spark, rows), path).where("not exact").count() == sum("▁" in (t or "") for _, t in rows)


def test_viterbi_equals_plain_dynamic_programming():
    r = random.Random(3)
    table = [("<unk>", 0.0, pieces.UNKNOWN)] + [(x, -r.random() * 5 - len(x) * 0.1, pieces.NORMAL) for x in ["▁", "a", "b", "ab", "▁a", "aba", "bb", "▁ab", "abab", "ba", "bab"]]
    model = pieces.Model(table, pieces.UNIGRAM)
    score = {p: (s, i) for i, (p, s, k) in enumerate(table) if k == pieces.NORMAL}

    def plain(t):
        t = "▁" + t.replace(" ", "▁") if t else ""
        best = [(0.0, [])]
        for end in range(1, len(t) + 1):
            options = [(best[a][0] + score[t[a:end]][0], best[a][1] + [score[t[a:end]][1]]) for a in range(end) if t[a:end] in score]
            if t[end - 1] not in score:
                options.append((best[end - 1][0] + model.unknown_score, best[end - 1][1] + [0]))
            best.append(max(options, key=lambda x: x[0]))
        return best[-1][1]

    rows = ["".join(r.choice("abbac ") for _ in range(r.randint(0, 30))) for _ in range(200)]
    ids, cuts = model.encode(pa.array(rows))
    by_id = {i: s for s, i in score.values()} | {0: model.unknown_score}
    for x, a, b in zip(rows, cuts[:-1], cuts[1:], strict=True):  # equally good ways may differ
        want = plain(x)
        assert sum(by_id[i] for i in want) == pytest.approx(sum(by_id[int(i)] for i in ids[a:b]))
        assert sum(len(table[i][0]) if i else 1 for i in want) == sum(len(table[int(i)][0]) if i else 1 for i in ids[a:b])


def test_top_k(spark):
    inf = float("inf")
    rows = [(20 * i if i % 3 else 20 * i + 1, [float((i * 7) % 5), float(i % 3), 1.5][: 1 + i % 3]) for i in range(60)]
    rows += [(None, [9.0, 9.0, 9.0]), (40, None), (60, [None, 1.0]), (80, [inf]), (100, []), (20, [7.0, 1.0, 1.5]), (20, [7.0, 1.0, 1.5])]
    table = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("score", F.lit("clash"))
    for shard in (10, 10**6):
        out = collections.Counter(tuple(r) for r in topk_search.top_k(table, F.col("id") % 20 == 0, k=5, shard_rows=shard).select("query_id", "rank", "vec_id", "score").collect())
        v = [(i, [int(np.floor(64 * x)) for x in e]) for i, e in rows if e is not None and all(x is not None and abs(x) < 1e30 for x in e)]
        want = collections.Counter()
        for q, x in {(i, tuple(e)) for i, e in v if i is not None and i % 20 == 0}:
            best = sorted(((-sum(a * b for a, b in zip(x, y, strict=False)), brute.ident(j), j) for j, y in v if j != q), key=lambda z: z[:2])[:5]
            want.update((q, r + 1, j, -s) for r, (s, _, j) in enumerate(best))
        assert out == want


def test_mix_follows_targets_and_reruns_agree(spark, sf, texts):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    out = mixing.mix(docs).collect()
    assert sorted(out) == sorted(mixing.mix(docs.repartition(7)).collect())
    by = collections.defaultdict(list)
    for r in out:
        by[r["source"]].append(r)
        assert 0 <= r["taken"] <= 2 * r["size"]
    total = sum(r["size"] for r in out)
    assert abs(sum(rs[0]["target"] for rs in by.values()) - 1.5 * total) < 1e-6 * total
    for rs in by.values():
        assert abs(sum(r["taken"] for r in rs) - rs[0]["target"]) <= max(r["size"] for r in rs)
    odd = mixing.mix(frame(spark, texts)).count()
    assert odd == len(texts)
    picked = mixing.mixed_documents(frame(spark, texts))
    assert picked.columns == frame(spark, texts).columns and picked.count() >= len(texts) - 5


def test_rules_by_join_equal_rules_inline(spark):
    urls = [(1, "https://EN.Example.com/en/71?x"), (2, "http://a.net/de/8"), (3, "http://example.net/de/81"), (4, "x.org/es/1"), (5, None), (6, "ftp://notcom/en/"), (7, "http://com/en/"), (8, "http://b.org#/es/"), (8, "http://b.org/es/")]
    pages = spark.createDataFrame(urls, "page_id long, url string").withColumn("host", F.lit("clash"))
    want = {1: ("en.example.com", "/en/71", "example.com/en/7", "allow"), 2: ("a.net", "/de/8", "net/de/", "allow"), 3: ("example.net", "/de/81", "example.net/de/8", "block"), 4: ("", "", None, "allow"), 5: ("", "", None, "allow"), 6: ("notcom", "/en/", None, "allow"), 7: ("com", "/en/", "com/en/", "block")}
    inline = sorted(map(tuple, url_rules.judged(pages, url_rules.RULES).collect()), key=repr)
    assert all(want[r[0]] == r[1:] for r in inline if r[0] in want)
    many = url_rules.RULES + [("block", f"h{i}.example", f"/p{i}/") for i in range(url_rules.INLINE)]
    assert sorted(map(tuple, url_rules.judged(pages, many).collect()), key=repr) == inline
    assert url_rules.kept_pages(pages, url_rules.RULES).columns == pages.columns


def test_classifier_against_labels(spark, sf, texts):
    folder = sf.replace("sf0.001", "sf0.01")
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    scorer, known = quality.trained(docs)
    out = quality.judged(docs, scorer).join(spark.read.parquet(f"{folder}/labels.parquet"), "doc_id").collect()
    good = [r["kept"] for r in out if r["quality"] == 1]
    bad = [r["kept"] for r in out if r["quality"] == 0]
    assert sum(good) >= 0.99 * len(good) and sum(bad) <= 0.1 * len(bad)
    assert set(known["labellers"]) == set(quality.LABELLERS)
    odd = quality.judged(frame(spark, texts), scorer)
    assert odd.count() == len(texts) and odd.where("doc_id in (901, 902, 905) and not kept").count() == 3
    assert quality.accepted(frame(spark, texts), scorer).columns == frame(spark, texts).columns


def test_empty_tables(spark):
    none = spark.createDataFrame([], SCHEMA)
    for f in (substring_dedup.repeated_words, suffix_dedup.repeated_bytes, exact_dedup.duplicate_classes, jaccard_join.linked_documents, mixing.mix):
        assert f(none).count() == 0
    assert token_counts.count_tokens(none, public_tokenizers.path(COUNTED_WITH)).count() == 0
    assert pieces.round_trip(none, public_tokenizers.path(ENCODED_WITH)).count() == 0
    assert quality.judged(none, quality.trained(none)[0]).count() == 0
    assert topk_search.top_k(spark.createDataFrame([], "vec_id long, embedding array<float>"), F.col("id") % 20 == 0).count() == 0
    assert url_rules.judged(spark.createDataFrame([], "page_id long, url string"), url_rules.RULES).count() == 0


def test_pipeline_stages(spark, sf):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, now = docs.columns, docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = {r.doc_id for r in now.select("doc_id").collect()}
        now = spark.createDataFrame(stage(spark, now, sf).collect(), docs.schema)
        assert now.columns == columns and {r.doc_id for r in now.select("doc_id").collect()} <= before, name
    rows = [(r.doc_id, r.text) for r in now.dropDuplicates(["doc_id"]).collect()]
    assert all(c == d for d, _, c in brute.linked(rows, 5, 80))
    assert corpus_pipeline.run(spark, sf).count() == now.count()
