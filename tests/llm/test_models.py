"""Quality, language, toxicity and n-gram scores: brute force where it exists, planted cases and held-out rows elsewhere."""

import collections
import itertools
import math
import random
import re
import zlib
from fractions import Fraction

import numpy as np
import public_tokenizers as P
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from levelwave.llm import bloom_lm, langid, quality, toxicity
from levelwave.llm.textkernel import texts_of

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = str.maketrans({chr(65 + i): chr(97 + i) for i in range(26)})


def counts(text):
    text = text or ""
    words = WORD.findall(text)
    grams = [tuple(words[i : i + 5]) for i in range(len(words) - 4)]
    times, cover = collections.Counter(grams), set()
    for i, g in enumerate(grams):
        if times[g] > 1:
            cover.update(range(i, i + 5))
    seen, dup = set(), 0
    for line in text.split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    return len(words), sum(map(len, words)), sum(text.count(c) for c in "#*$%&|<>"), dup, len(cover)


def test_counts_equal_brute_force():
    rng = random.Random(5)
    atoms = ["a", "b", " ", "  ", "\n", "\n\n", "c d e f g ", "#", "é", "\t", "\x0b", "\x85", "A", "x" * 70, "😀"]
    texts = [None, "", "\n"] + ["".join(rng.choice(atoms) for _ in range(rng.randint(0, 80))) for _ in range(800)]
    got = quality.statistics(texts_of(pa.array(texts, pa.string())))
    assert [tuple(int(got[c][k]) for c in quality.COUNTS) for k in range(len(texts))] == [counts(t) for t in texts]


def test_outliers_are_rejected_and_clean_rows_kept(spark):
    rng = random.Random(6)
    words = ["".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 9))) for _ in range(3000)]
    rows = []
    for i in range(900):
        text = " ".join(rng.choice(words) for _ in range(rng.randint(30, 300))).capitalize() + "."
        if i % 30 == 0:
            text = " ".join(w + rng.choice(["$$$", "###", "&&&"]) for w in text.split())
        rows.append((i, text, rng.choice(["en", "de", None]), rng.choice(["s0", "s0", "s1", "rare" if i % 200 == 0 else "s1"]), 0))
    rows += [(9001, None, "en", "s0", 0), (9002, "too short", "en", "s0", 0), (None, rows[1][1], None, None, 0), (9003, "same five words here again " * 9, "en", "s0", 0)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, distance int")
    got = {r["doc_id"]: r for r in quality.judged(df.drop("distance").withColumn("x0", F.lit(1))).collect()}
    assert len(got) == len(rows)
    bad = {i for i in range(900) if i % 30 == 0} | {9001, 9002, 9003}
    assert {i for i, r in got.items() if not r["kept"]} == bad
    assert got[9003]["base_failed"] and got[9001]["n_words"] == 0 and got[None]["kept"]
    assert {r["doc_id"] for r in quality.drop_rejected(df).collect()} == set(got) - bad
    assert quality.judged(df.limit(0)).isEmpty()


def planted_rows(clean=600, each=20):
    """(doc_id, text, lang, source): clean rows with ids from 0, then rows of one fault each, from 1000, 2000 and so on."""
    rng = random.Random(12)
    word = lambda n: "".join(rng.choice("abcdefghij") for _ in range(n))
    texts = {i: "\n".join(" ".join(word(rng.randint(2, 9)) for _ in range(rng.randint(3, 6))) for _ in range(40)) for i in range(clean)}
    for i in range(each):
        base = texts[i].split("\n")
        once = [word(8) for _ in range(20)]
        lines = [x for k, w in enumerate(once) for x in (w, once[0] if k else word(3))]
        texts[1000 + i] = "\n".join(lines)  # half of the lines are repeated, no window of five words is
        texts[2000 + i] = "\n".join("".join(c.upper() if rng.random() < 0.15 else c for c in x) for x in base)
        texts[3000 + i] = "\n".join("".join("," if rng.random() < 0.15 else c for c in x) for x in base)
        texts[4000 + i] = "\n".join("".join("#" if c != " " and rng.random() < 0.08 else c for c in x) for x in base)
        texts[5000 + i] = "\n".join(" ".join(word(rng.randint(20, 50)) for _ in x.split()) for x in base)
    return [(i, t, "en", "s0") for i, t in texts.items()]


def test_one_fault_is_enough_in_a_clean_cell(spark):
    rows = planted_rows()
    got = {r["doc_id"]: r for r in quality.judged(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")).collect()}
    assert not any(r["base_failed"] for r in got.values())
    recall = {kind: sum(not got[i]["kept"] for i in got if i // 1000 == kind) / 20 for kind in range(1, 6)}
    assert min(recall.values()) == 1, recall
    assert sum(not r["kept"] for i, r in got.items() if i < 1000) <= 0.005 * 600


def brute_determinant(x, h):
    """The least log determinant over all subsets of h rows, with the factor and floor of the operator."""
    best = math.inf
    for subset in itertools.combinations(range(len(x)), h):
        cov = np.cov(x[list(subset)].T, bias=True) * quality.consistency(h / len(x)) + np.eye(x.shape[1]) * quality.FLOOR**2
        best = min(best, np.linalg.slogdet(cov)[1])
    return best


def test_small_cells_reach_the_least_determinant(spark):
    rng = np.random.default_rng(7)
    cells, rows = {}, []
    for k in range(6):
        x = rng.normal(size=(16, quality.D)) @ (np.eye(quality.D) * 2 + rng.normal(size=(quality.D, quality.D)))
        x[:4] += rng.normal(size=quality.D) * 25  # a quarter lies elsewhere
        cells[f"c{k}"] = x
        rows += [(f"c{k}", *map(float, v)) for v in x]
    df = spark.createDataFrame(rows, "cell string, " + ", ".join(f"x{i} double" for i in range(quality.D))).repartition(3)
    got = {r["cell"]: r for r in quality.estimate(df, weighed=None).collect()}
    for name, x in cells.items():
        assert got[name]["logdet"] <= brute_determinant(x, 12) + 0.5, name
        d = x - np.array(got[name]["mean"])
        far = np.einsum("ni,ij,nj->n", d, np.array(got[name]["inverse"]).reshape(quality.D, -1), d)
        assert far[:4].min() > far[4:].max(), name
    near = [abs(got[name]["logdet"] - brute_determinant(x, 12)) < 0.05 for name, x in cells.items()]
    assert sum(near) >= 4  # it may end beside the least one, never far from it


def test_verdicts_equal_a_plain_estimate(spark):
    """One clean cell: the same steps in numpy over exact distances, to the end, then all rows within the quantile."""
    rows = planted_rows(clean=200, each=8)
    got = {r["doc_id"]: r for r in quality.judged(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")).collect()}
    x = quality.statistics(texts_of(pa.array([t for _, t, *_ in rows])))["x"]
    h, near = int(0.75 * len(x)), np.argsort((((x - np.median(x, axis=0)) / (np.std(x, axis=0) + 0.3)) ** 2).sum(axis=1))
    for _ in range(50):
        part = x[near[:h]]
        cov = np.cov(part.T, bias=True) * quality.consistency() + np.eye(quality.D) * quality.FLOOR**2
        d = x - part.mean(axis=0)
        near = np.argsort(far := np.einsum("ni,ij,nj->n", d, np.linalg.inv(cov), d))
    part = x[far <= quality.chi2_tail_point(0.025, quality.D)]
    d, cov = x - part.mean(axis=0), np.cov(part.T, bias=True) * quality.consistency(0.975) + np.eye(quality.D) * quality.FLOOR**2
    far = np.einsum("ni,ij,nj->n", d, np.linalg.inv(cov), d)
    for (i, *_), f in zip(rows, far, strict=True):
        assert got[i]["distance"] == pytest.approx(f, rel=0.1, abs=0.05), i
        assert got[i]["kept"] == (f <= quality.chi2_tail_point(quality.TAIL, quality.D)) or abs(f - 22.5) < 2


def test_null_names_are_cells_of_their_own(spark):
    rng = random.Random(3)
    text = lambda long: " ".join("".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 9) * long)) for _ in range(120))
    rows = [(i, text(1), "en", "s") for i in range(100)] + [(1000 + i, text(6), None, "s") for i in range(100)] + [(2000 + i, text(1), f"l{i % 2}", "s") for i in range(60)]
    rows += [(None, text(6), "en", "s"), (None, text(1), "en", "s"), (7, text(6), "en", "s")]  # a null id, and one id with two texts
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    got = [(r["doc_id"], r["kept"]) for r in quality.judged(df).collect()]
    assert all(k for i, k in got if i is not None and i != 7)  # long words are natural among the null ones, short ones in the others
    assert sorted(k for i, k in got if i is None) == sorted(k for i, k in got if i == 7) == [False, True]
    left = quality.drop_rejected(df).collect()
    assert len(left) == len(rows) - 2 and sum(r["doc_id"] is None for r in left) == 1 and sum(r["doc_id"] == 7 for r in left) == 1


def test_chi_square_by_known_values():
    assert quality.chi2_cdf(12.592, 6) == pytest.approx(0.95, abs=1e-4)
    assert quality.chi2_tail_point(0.05, 6) == pytest.approx(12.592, abs=1e-3)
    assert quality.consistency(0.999999) == pytest.approx(1, abs=1e-3)


@pytest.fixture(scope="module")
def pieces():
    return langid.Pieces(P.path("piece_bpe_32k.model"))


def ways(pieces, word, table):
    """The sums of all segmentations of a word with its mark, by exact fractions: one for each language."""
    names = {pieces.library.id_to_piece(i): i for i in range(pieces.size)}
    known = {p for p in names if p == "▁" or p.removeprefix("▁") and all(map(langid._in_word, p.removeprefix("▁")))}
    full, sums = "▁" + word, [np.array([Fraction(1)] * table.shape[1])]
    exact = {}
    for t in range(1, len(full) + 1):
        total = np.array([Fraction(0)] * table.shape[1])
        for n in range(1, min(t, pieces.longest) + 1):
            part = full[t - n : t]
            if part in known:
                total += sums[t - n] * exact.setdefault(part, np.array([Fraction(float(x)) for x in table[names[part]]]))
            elif n == 1:
                total += sums[t - 1] * Fraction(langid.UNKNOWN)
        sums.append(total)
    return [math.log(x.numerator) - math.log(x.denominator) for x in sums[-1]]


def test_forward_sum_equals_all_segmentations(pieces):
    rng = np.random.default_rng(2)
    table = rng.dirichlet(np.full(pieces.size, 0.3), 3).T
    words = ["the", "an", "vous", "straße", "q", "zzzz", "漢字", "", "Ж漢q"]
    letters = list("aeinrstlo") * 4 + list("ßé漢Ж")
    words += ["".join(rng.choice(letters, n)) for n in (30, 31, 32, 33, 47, 60, 63, 64, 65, 95, 128, 200)]
    words += ["donaudampfschifffahrtsgesellschaftskapitaen", "the" * 21, "a" * 130]
    got = pieces.log_probabilities(words, table)
    for k, word in enumerate(words):
        assert got[k] == pytest.approx(ways(pieces, word, table), rel=1e-9), word
    # All cuts written out, for a short word: the same sum as by the recursion above.
    names = {pieces.library.id_to_piece(i): i for i in range(pieces.size)}
    total, full = np.zeros(3), "▁vous"
    for cuts in itertools.product([0, 1], repeat=len(full) - 1):
        ends = [0, *(i + 1 for i, c in enumerate(cuts) if c), len(full)]
        parts = [full[a:b] for a, b in itertools.pairwise(ends)]
        if all(p in names for p in parts):
            total += np.prod([table[names[p]] for p in parts], axis=0)
    assert np.exp(got[2]) == pytest.approx(total, rel=1e-9)
    long = "".join(rng.choice(letters, 20_000))
    once = pieces.log_probabilities([long, "a"], table)
    assert np.isfinite(once).all() and once[1] == pytest.approx(ways(pieces, "a", table))
    # However the spans fall and however many are held together, the sum is the same.
    try:
        langid.SPAN, langid.HELD = 37, 1
        assert pieces.log_probabilities([long[:900], "a"], table)[0] == pytest.approx(ways(pieces, long[:900], table), rel=1e-9)
    finally:
        langid.SPAN, langid.HELD = 64, 32 << 20


def test_expected_counts_equal_all_segmentations(pieces):
    rng = np.random.default_rng(5)
    table = rng.dirichlet(np.full(pieces.size, 0.3))
    names = {pieces.library.id_to_piece(i): i for i in range(pieces.size)}
    words, times = ["vous", "the", "an"], [3, 1, 7]
    want = np.zeros(pieces.size)
    for word, n in zip(words, times):
        full, ways_, sums = "▁" + word, [], []
        for cuts in itertools.product([0, 1], repeat=len(full) - 1):
            ends = [0, *(i + 1 for i, c in enumerate(cuts) if c), len(full)]
            parts = [full[a:b] for a, b in itertools.pairwise(ends)]
            if all(p in names for p in parts):
                ways_.append([names[p] for p in parts])
                sums.append(math.prod(table[names[p]] for p in parts))
        for way, x in zip(ways_, sums):
            np.add.at(want, way, n * x / sum(sums))
    assert pieces.expected(words, np.array(times), table) == pytest.approx(want, rel=1e-6, abs=1e-9)


def test_marks_belong_to_words():
    assert langid.letters_of("हिन्दी,") == "हिन्दी" and langid.letters_of("12́") == "" and langid.letters_of("It's") == "its"


def test_languages_of_held_out_rows(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    extra = spark.createDataFrame([(1_000_001, None, "en", "s", 0), (1_000_002, "123 ... 45", "fr", "s", 0), (None, "de la maison est", None, "s", 0)], docs.schema)
    got = langid.language(docs.unionByName(extra), P.path("piece_bpe_32k.model"), most=200).join(docs.select("doc_id", "lang"), "doc_id", "left").collect()
    held = [r for r in got if r["held_out"] and r["lang"] and r["lang_pred"] != "und"]
    assert len(held) > 150 and sum(r["lang_pred"] == r["lang"] for r in held) / len(held) > 0.97
    assert {r["lang_pred"] for r in got if r["doc_id"] in (1_000_001, 1_000_002)} == {"und"}
    assert all(0 <= r["score"] <= 1 for r in got) and all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) for r in got if r["doc_id"] is not None)
    empty = langid.language(docs.limit(0), P.path("piece_bpe_32k.model"))
    assert empty.isEmpty()
    nothing = langid.language(docs.limit(3).withColumn("lang", F.lit(None).cast("string")), P.path("piece_bpe_32k.model")).collect()
    assert {r["lang_pred"] for r in nothing} == {"und"}


def test_fit_equals_a_plain_ftrl():
    """The update rule written out, one coordinate at a time in plain Python."""
    rng = random.Random(2)
    settings = toxicity.Settings(alpha=0.7, beta=1.5, l1=0.8, l2=0.3, epochs=3, positive=2.0, bits=6)
    rows = [(sorted(rng.sample(range(64), rng.randint(0, 9))), rng.randint(0, 1)) for _ in range(120)]
    z, n = collections.defaultdict(float), collections.defaultdict(float)

    def weight(i):
        if i == "bias":
            return -z[i] / ((1.5 + math.sqrt(n[i])) / 0.7)
        return 0.0 if abs(z[i]) <= 0.8 else -(z[i] - math.copysign(0.8, z[i])) / ((1.5 + math.sqrt(n[i])) / 0.7 + 0.3)

    for _ in range(3):
        for buckets, label in rows:
            w = {i: weight(i) for i in [*buckets, "bias"]}
            g = (1 / (1 + math.exp(-sum(w.values()))) - label) * (2.0 if label else 1.0)
            for i, x in w.items():
                z[i] += g - (math.sqrt(n[i] + g * g) - math.sqrt(n[i])) / 0.7 * x
                n[i] += g * g
    bias, live, w = toxicity.fit([(np.array(b, dtype=np.int64), y) for b, y in rows], settings)
    want = {i: weight(i) for i in range(64) if weight(i)}
    assert bias == pytest.approx(weight("bias")) and dict(zip(live.tolist(), w)) == pytest.approx(want) and 0 < len(want) < 64


def test_training_text_is_bounded_in_bytes(spark):
    docs = spark.createDataFrame([(i, "x" * 100) for i in range(60)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, 0, i % 2) for i in range(60)], "doc_id long, quality int, toxic int")
    every = toxicity.training_rows(docs, labels).collect()
    some = toxicity.training_rows(docs, labels, most_bytes=1050).collect()
    assert len(every) > 30 and len(some) == 10 and {r["doc_id"] for r in some} < {r["doc_id"] for r in every}
    assert all(len(r["text"]) == 100 for r in some)


def test_toxic_words_are_learned_from_allowed_rows_only(spark):
    rng = random.Random(8)
    words = [f"w{k}" for k in range(400)]
    docs, labels = [], []
    for i in range(1500):
        text, toxic = [rng.choice(words) for _ in range(40)], i % 5 == 0
        if toxic:
            text[rng.randrange(40)] = rng.choice(["Foul,", "nasty", "vile!"])
        docs.append((i, " ".join(text)))
        labels.append((i, 1, int(toxic)))
    docs += [(5001, None), (None, "nasty foul vile")]
    labels += [(3, 1, None), (None, 1, 1)]
    d, lab = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    got = toxicity.toxicity(d.withColumn("score", F.lit("x")), lab).collect()
    assert len(got) == len(docs)
    held = [r for r in got if r["held_out"]]
    assert all((zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in held)
    wrong = [r["doc_id"] for r in held if r["predicted"] != (r["doc_id"] % 5 == 0 and r["doc_id"] < 1500)]
    assert len(wrong) <= 0.01 * len(held)
    kept = {r["doc_id"] for r in toxicity.drop_toxic(d, lab).collect()}
    assert kept >= {i for i in range(1500) if i % 5} - set(wrong) and None not in kept
    flipped = lab.withColumn("toxic", F.when(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, 1 - F.col("toxic")).otherwise(F.col("toxic")))
    again = {r["doc_id"]: r["score"] for r in toxicity.toxicity(d, flipped).collect()}
    assert again == {r["doc_id"]: r["score"] for r in got}  # held-out labels don't matter
    none = toxicity.toxicity(d, lab.limit(0)).collect()
    assert {r["score"] for r in none} == {0.0}
    assert toxicity.toxicity(d.limit(0), lab).isEmpty()


@pytest.mark.parametrize("head", [1 << 20, 64])
def test_base_scores_equal_brute_force(spark, small, monkeypatch, head):
    monkeypatch.setattr(bloom_lm.build, "__defaults__", (bloom_lm.FILTER_BYTES, head))
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text")
    docs = docs.unionByName(spark.createDataFrame([(70_001, None), (70_002, " "), (None, "The end")], docs.schema))
    rows = [(r["doc_id"], WORD.findall((r["text"] or "").translate(LOWER)) + [None]) for r in docs.collect()]
    held = {i: i is None or zlib.crc32(str(i).encode()) % 10 == 0 for i, _ in rows}
    c = collections.Counter(t for i, ts in rows if not held[i] for t in ts)
    n, v = sum(c.values()), len(c)
    got = {r["doc_id"]: r for r in bloom_lm.bloom_scores(docs, segments=5).collect()}
    assert len(got) == len(rows)
    for i, ts in rows:
        r = got[i]
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (held[i], len(ts), sum(c[t] > 0 for t in ts), n)
        assert r["base_score"] == pytest.approx(sum(math.log10((c[t] + 0.1) / (n + 0.1 * (v + 1))) for t in ts), rel=1e-9)
        assert r["score"] < 0
    mean = lambda k: sum(r[k] for r in got.values() if r["held_out"]) / sum(r["n_tokens"] for r in got.values() if r["held_out"])
    assert mean("score") > mean("base_score")


def test_filter_never_forgets_a_level(spark):
    rng = np.random.default_rng(0)
    keys, counts = np.unique(rng.integers(0, 2**64, 5000, dtype=np.uint64)), None
    counts = rng.integers(1, 3000, len(keys))
    parts = [keys[bloom_lm.segment_of(keys, 7) == s] for s in range(7)]
    model = bloom_lm.LogFrequencyFilter.of([bloom_lm.filled(p, counts[np.searchsorted(keys, p)]) for p in parts])
    assert (model.levels(keys) >= bloom_lm._levels(counts)).all() and (model.levels(keys) == bloom_lm._levels(counts)).mean() > 0.95
    strangers = rng.integers(0, 2**64, 5000, dtype=np.uint64)
    assert (model.levels(strangers) > 0).mean() < 0.05
    assert (bloom_lm._least(bloom_lm._levels(counts)) <= counts).all() and (counts <= bloom_lm._most(bloom_lm._levels(counts))).all()
    assert (bloom_lm.unpacked(bloom_lm.packed(keys)) == keys).all() and (bloom_lm.from_planes(bloom_lm.planes(counts), np.int64) == counts).all()


@pytest.mark.parametrize("head", [1 << 20, 3])
def test_scores_equal_a_brute_force_model_and_add_up(spark, monkeypatch, head):
    """Without false positives (none at this size) a score is that of levels of counts by dictionary; all next words of a
    context, the unknown one among them, have a probability of 1 at most together."""
    monkeypatch.setattr(bloom_lm, "BITS_PER_ENTRY", 200)
    monkeypatch.setattr(bloom_lm.build, "__defaults__", (bloom_lm.FILTER_BYTES, head))
    texts = ["a b a b c", "a b b d", "e a", "", "c c c c c c c", "b a d a b"]
    train = spark.createDataFrame([(i, t) for i, t in zip((i for i in range(1, 99) if zlib.crc32(str(i).encode()) % 10), texts * 3)], "doc_id long, text string")
    runs = [("<", *t.split(), ">") for t in texts * 3]
    words = collections.Counter(w for r in runs for w in r[1:])
    pairs = collections.Counter(p for r in runs for p in itertools.pairwise(r))
    n, v = sum(words.values()), len(words)
    low, high = (lambda c: 2 ** int(math.log2(c)) if c else 0), (lambda c: 2 ** (int(math.log2(c)) + 1) - 1 if c else 0)
    level = sorted((int(math.log2(c)) for c in words.values()), reverse=True)
    cut = next(k for k in range(64) if sum(x >= k for x in level) <= head)
    known = {w: int(math.log2(c)) >= cut for w, c in words.items()}

    def probability(first, second):
        count = words[second] if known.get(second, True) else low(words[second])
        single = (count + 0.1) / (n + 0.1 * (v + 1))
        context = ">" if first == "<" else first
        under = words[context] if known.get(context, True) else high(words[context])
        return 0.6 * min(low(pairs[first, second]) / under, 1) + 0.4 * single if under else single

    for first in ["<", *words, "zz"]:
        if first != ">":
            assert sum(probability(first, w) for w in [*words, "zz"]) <= 1 + 1e-9
    asked = ["a b c", "zz a zz", "", "c c e"]
    held = [i for i in range(99) if not zlib.crc32(str(i).encode()) % 10][: len(asked)]
    docs = train.unionByName(spark.createDataFrame(list(zip(held, asked)), train.schema))
    got = {r["doc_id"]: r["score"] for r in bloom_lm.bloom_scores(docs, segments=3).collect()}
    for i, t in zip(held, asked):
        want = sum(math.log10(probability(*p)) for p in itertools.pairwise(("<", *t.split(), ">")))
        assert got[i] == pytest.approx(want, rel=1e-9), t


@pytest.mark.parametrize("head", [1 << 20, 64])
def test_a_filter_past_the_broadcast_bound_scores_alike(spark, small, monkeypatch, head):
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text")
    docs = docs.unionByName(spark.createDataFrame([(70_001, None), (70_002, " "), (None, "The end")], docs.schema))
    order = lambda df: sorted(df.collect(), key=lambda r: (r["doc_id"] is None, r["doc_id"]))
    monkeypatch.setattr(bloom_lm.build, "__defaults__", (bloom_lm.FILTER_BYTES, head))
    want = order(bloom_lm.bloom_scores(docs, segments=5))
    monkeypatch.setattr(bloom_lm.build, "__defaults__", (24, head))
    monkeypatch.setattr(bloom_lm, "BLOCK", 5000)
    got = order(bloom_lm.bloom_scores(docs, segments=5))
    assert len(got) == len(want) and [r["doc_id"] for r in got] == [r["doc_id"] for r in want]
    for a, b in zip(got, want, strict=True):
        assert (a["n_tokens"], a["n_known"], a["score"]) == (b["n_tokens"], b["n_known"], pytest.approx(b["score"], rel=1e-12))
        assert a["base_score"] == pytest.approx(b["base_score"], rel=1e-9)


def test_pairs_seen_once_are_entered(spark):
    parts = bloom_lm.learned(spark.createDataFrame([(1, "one two three")], "doc_id long, text string"), 2)
    model = bloom_lm.build(parts, 2)
    _, hashes, before = bloom_lm.tokens(texts_of(pa.array(["one two three"])))
    assert (model.filter.levels(bloom_lm.pair_hash(before, hashes)) > 0).all()


def test_nothing_to_learn_from(spark):
    docs = spark.createDataFrame([(None, "a b")], "doc_id long, text string")
    r = bloom_lm.bloom_scores(docs).first()
    assert (r["n_tokens"], r["n_known"], r["train_tokens"], r["held_out"]) == (3, 0, 0, True) and r["score"] == pytest.approx(r["base_score"])
    assert bloom_lm.bloom_scores(docs.limit(0)).isEmpty()
