"""Exact and near duplicates against brute force; pieces of the pipeline that follow from them."""

import hashlib
import random
import re

import numpy as np
import pytest

from levelwave.llm import exact, minhash
from levelwave.llm.textkernel import WHITE_TABLE, runs, shingle_sets, texts_of

SPACE = re.compile(r"[\x20\x09-\x0D]+")
LOWER = str.maketrans({chr(65 + i): chr(97 + i) for i in range(26)})


def shingles(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(LOWER))
    return {tuple(words[i : i + 5]) for i in range(len(words) - 4)} if len(words) >= 5 else ({tuple(words)} if words else set())


def near_brute(docs):
    sets, root = {i: shingles(t) for i, t in docs}, {i: i for i, _ in docs}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for k, a in enumerate(ids):
        for b in ids[:k]:
            both = len(sets[a] & sets[b])
            if both and 100 * both >= 75 * (len(sets[a]) + len(sets[b]) - both):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {i: (len(sets[i]), find(i)) for i in ids}


def made_up(seed, n=160):
    rng = random.Random(seed)
    base = [[f"w{rng.randint(0, 400)}" for _ in range(rng.choice([3, 8, 40, 120]))] for _ in range(20)]
    passage = [f"p{k}" for k in range(40)]
    out = [None, "", " \n", "one", "One", "a b c d", "A b  c D", "a b c d e"]
    for _ in range(n):
        words = list(rng.choice(base))
        for _ in range(rng.choice([0, 0, 1, 2, 5])):
            words[rng.randrange(len(words))] = f"x{rng.randint(0, 5)}"
        if rng.random() < 0.2:
            words = words[: len(words) // 2] + passage + words[len(words) // 2 :]
        out.append(rng.choice([" ", "  ", "\n"]).join(words))
    return list(enumerate(out))


@pytest.mark.parametrize("seed", [1, 2])
def test_near_duplicates_equal_brute_force(spark, seed):
    docs = made_up(seed)
    df = spark.createDataFrame([(i, t, 7) for i, t in docs], "doc_id long, text string, component_id int").repartition(5)
    got = {r["doc_id"]: r for r in minhash.near_duplicates(df).collect()}
    want = near_brute(docs)
    assert {i: (r["n_shingles"], r["component_id"]) for i, r in got.items()} == want
    assert all(r["kept"] == (i == r["component_id"]) for i, r in got.items())
    kept = {r["doc_id"] for r in minhash.drop_near_copies(df).collect()}
    assert kept == {i for i, (_, c) in want.items() if i == c}


def test_chains_of_links_and_edge_rows(spark):
    words = [f"c{k}" for k in range(100)]
    chain = []
    for k in range(12):  # each is near the next, the ends are far apart
        words = words[:8 * k] + [f"n{k}{j}" for j in range(6)] + words[8 * k + 6 :]
        chain.append((k, " ".join(words)))
    df = spark.createDataFrame([*chain, (None, chain[0][1]), (0, chain[0][1])], "doc_id long, text string")
    got = minhash.near_duplicates(df).collect()
    assert len(got) == 14 and {r["component_id"] for r in got if r["doc_id"] is not None} == set(c for _, c in near_brute(chain).values())
    assert [r["component_id"] for r in got if r["doc_id"] is None] == [None]
    assert minhash.near_duplicates(df.limit(0)).isEmpty()


def test_recall_of_the_sketch():
    rng = np.random.default_rng(3)
    hits = total = 0
    for _ in range(300):
        common, own = rng.integers(0, 2**63, 150, dtype=np.uint64), rng.integers(0, 2**63, 50, dtype=np.uint64)
        a, b = np.unique(np.concatenate((common, own[:25]))), np.unique(np.concatenate((common, own[25:])))
        keys = minhash.band_keys(np.stack([minhash.signature(a), minhash.signature(b)]))
        hits += bool((keys[0] == keys[1]).any())
        total += 1
    assert hits == total  # similarity 0.75


def test_circulant_coordinates_are_shifts():
    table = minhash.circle(1 << 12, 16)
    assert (table[5][1:] == table[6][:-1]).all() and table.shape[1] == 16


def test_shingles_equal_words(small):
    import duckdb
    import pyarrow as pa

    texts = [r[0] for r in duckdb.sql(f"SELECT text FROM '{small}/documents.parquet'").fetchall()] + ["", None, "a b", "A B"]
    sets = shingle_sets(runs(texts_of(pa.array(texts)), WHITE_TABLE))
    assert [len(s) for s in sets] == [len(shingles(t)) for t in texts]
    assert (sets[-1] == sets[-2]).all()


def exact_brute(docs):
    groups = {}
    for i, t in docs:
        groups.setdefault(SPACE.sub(" ", t or ""), []).append(i)
    return {i: (min(g), len(g), i == min(g), hashlib.sha256(k.encode()).hexdigest()) for k, g in groups.items() for i in g}


def test_exact_copies_equal_brute_force(spark):
    rng = random.Random(4)
    docs = [(i, rng.choice([None, "", "a", "a b", "a  b", "a\n\tb", " a b", "A b", "é", "a\xa0b"])) for i in range(200)]
    df = spark.createDataFrame([(i, t, "x") for i, t in docs], "doc_id long, text string, keep_id string").repartition(7)
    got = {r["doc_id"]: (r["keep_id"], r["group_size"], r["kept"], r["text_sha256"]) for r in exact.exact_dedup(df).collect()}
    assert got == exact_brute(docs)
    assert {r["doc_id"] for r in exact.drop_copies(df).collect()} == {i for i, v in got.items() if v[2]}


def test_index_grows_by_batches(spark):
    index = exact.DigestIndex(spark, buckets=4)
    batch = lambda rows: spark.createDataFrame(rows, "doc_id long, text string")
    first = index.ingest(batch([(5, "a"), (6, "b"), (7, "b")])).collect()
    assert {(r["doc_id"], r["kept"]) for r in first} == {(5, True), (6, True), (7, False)}
    second = {r["doc_id"]: r for r in index.ingest(batch([(1, "a"), (2, "c"), (3, "c"), (None, "d")])).collect()}
    assert (second[1]["keep_id"], second[1]["kept"]) == (5, False)  # an earlier batch brought it
    assert second[2]["kept"] and not second[3]["kept"] and second[None]["kept"]
    assert index.table().count() == 4


def test_index_is_opened_again_and_a_batch_given_again(spark, tmp_path):
    batch = lambda rows: spark.createDataFrame(rows, "doc_id long, text string")
    said = lambda index, rows: sorted((r["doc_id"], r["keep_id"], r["kept"]) for r in index.ingest(batch(rows)).collect())
    path, top = f"file://{tmp_path}/index", 2**63 - 1
    rows = [(5, "a"), (6, "b"), (7, "b"), (top, "z")]
    want = [(5, 5, True), (6, 6, True), (7, 6, False), (top, top, True)]
    assert said(exact.DigestIndex(spark, path, buckets=4), rows) == want
    for open_index in (lambda: exact.DigestIndex(spark, path), lambda: exact.DigestIndex(spark.newSession(), path, buckets=9)):
        spark.sql(f"DROP TABLE {open_index().name}")  # as in a session that has never seen it
        index = open_index()
        assert index.buckets == 4 and index.table().count() == 3
        assert said(index, rows) == want  # a batch that is given again
        assert said(index, [(1, "a"), (8, "b")]) == [(1, 5, False), (8, 6, False)]
    # A batch whose append broke off: the digests that are there already are its own.
    index, fresh = exact.DigestIndex(spark, path), [(11, "k"), (12, "l"), (13, "l")]
    first = said(index, fresh)
    half = index.table().where("keep_id <> 11").collect()
    again = exact.DigestIndex(spark, f"{path}-2", buckets=4)
    again.append(spark.createDataFrame(half, exact.ENTRIES))
    assert said(again, fresh) == first == [(11, 11, True), (12, 12, True), (13, 12, False)]
    again.drop()
    assert not (tmp_path / "index-2").exists() and again.name not in [t.name for t in spark.catalog.listTables()]


def test_a_hot_text_is_dealt_over_keys(spark, monkeypatch):
    monkeypatch.setattr(exact, "HOT_ROWS", 10)
    docs = [(i, "hot" if i % 3 else f"t{i}") for i in range(1, 400)]
    got = {r["doc_id"]: (r["keep_id"], r["group_size"], r["kept"], r["text_sha256"]) for r in exact.exact_dedup(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == exact_brute(docs)


def test_repeated_rows_leave_one(spark):
    df = spark.createDataFrame([(1, "a", "en"), (1, "a", "en"), (None, "a", "en"), (None, "z", None), (None, "z", None)], "doc_id long, text string, lang string")
    got = exact.exact_dedup(df).collect()
    assert len(got) == 5 and sum(r["kept"] for r in got) == 2
    assert sorted(exact.drop_copies(df.coalesce(1)).collect(), key=repr) == sorted([(1, "a", "en"), (None, "z", None)], key=repr)
    assert exact.exact_dedup(df.limit(0)).isEmpty()


def test_family_around_the_similarity_equals_all_pairs(spark):
    """Variants of one text by a few words of a small vocabulary: many lie just under the similarity, some link only to each other."""
    import random as random_

    rng = random_.Random(23)
    base = [f"w{i}" for i in range(150)]
    texts = []
    for _ in range(140):
        words = list(base)
        for at in rng.sample(range(150), rng.choice([1, 2, 3, 4, 5, 6, 7])):
            words[at] = rng.choice(["aa", "bb", "cc"])
        texts.append(" ".join(words))
    sets = [frozenset(tuple(w[i : i + 5]) for i in range(len(w) - 4)) for w in map(str.split, texts)]
    root = list(range(len(sets)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, a in enumerate(sets):
        for j in range(i):
            if 100 * len(a & sets[j]) >= 75 * len(a | sets[j]):
                x, y = sorted((find(i), find(j)))
                root[y] = x
    from levelwave.llm.minhash import near_duplicates

    got = {r["doc_id"]: r["component_id"] for r in near_duplicates(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert got == {i: find(i) for i in range(len(texts))}
    assert len(set(got.values())) > 1
