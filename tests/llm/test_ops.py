"""The ten operators against brute force, round trips and held-out rows, with nulls, empties, repeats and empty tables."""

import collections
import gzip
import hashlib
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from blockgraph.llm import decontaminate, features, jaccard_join, language_id, language_model, media, sentencepiece_codec, sharding, token_counts, toxicity, warc
from blockgraph.llm.links import connected
from blockgraph.llm.text import ALNUM, SPACED, Tokens, fitting, utf8

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
LONG = "lorem Ipsum-dolor sit " * 3000
ODD = [None, "", " ", "\n", "a", "A b c", "x" * 5000, LONG, LONG, "é ▁ 日本 \x00 🙂", "one two three four five six seven eight nine ten eleven", "1 2 3"]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i if i != 4 else None, t, None if i % 3 else "en", None if i % 4 == 0 else "s", i) for i, t in enumerate(ODD)]
    return spark.createDataFrame([*rows, rows[5]], "doc_id long, text string, lang string, source string, n_chars long")


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")


@pytest.fixture(scope="module")
def real(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


def spaced(text):
    return [w for w in re.split(r"[\x20\x09-\x0d]+", (text or "").translate(LOWER)) if w]


def test_tokens_match_patterns():
    data, offs = utf8(pa.array(ODD, pa.string()))
    for alphabet, pattern in ((SPACED, rb"[^\x20\x09-\x0d]+"), (ALNUM, rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")):
        t = Tokens(data, offs, alphabet)
        for d, text in enumerate(ODD):
            want = re.findall(pattern, (text or "").translate(LOWER).encode())
            assert t.words(np.arange(t.first[d], t.first[d + 1])).to_pylist() == want
    h = Tokens(data, offs, SPACED).hashes()
    words = Tokens(data, offs, SPACED).words(np.arange(len(h))).to_pylist()
    assert len(set(words)) == len(set(h.tolist()))


# 1


def brute_hits(texts, items):
    pattern = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
    found = collections.defaultdict(set)
    for i, t in items:
        w = re.findall(pattern, (t or "").translate(LOWER))
        for k in range(max(1, len(w) - 9)) if w else ():
            found[tuple(w[k : k + 10])].add(i)
    for text in texts:
        w = re.findall(pattern, (text or "").translate(LOWER))
        hit, ids = set(), set()
        for n in {len(k) for k in found}:
            for k in range(len(w) - n + 1):
                if tuple(w[k : k + n]) in found:
                    hit |= set(range(k, k + n))
                    ids |= found[tuple(w[k : k + n])]
        yield len(w), len(hit), sorted(str(i) for i in ids if i is not None)


def test_decontamination(spark, docs, none):
    items = [(1, "two, three FOUR five six seven eight nine ten eleven"), (2, "b C"), (3, None), (4, ""), (None, "1 2"), (10, "B c")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = sorted(tuple(map(str, (r.n_words, r.n_hit, r["items"]))) for r in decontaminate.contamination_report(docs, bench).collect())
    want = sorted(tuple(map(str, x)) for x in brute_hits([*ODD, ODD[5]], items))
    assert got == want
    assert decontaminate.decontaminate(docs, bench).count() == len(ODD) + 1 - 4
    cut = {r.n_chars: r.text for r in decontaminate.decontaminate(docs, bench, "spans").collect()}
    assert cut[5] == "A " and cut[11] == " 3" and cut[7] == LONG
    assert decontaminate.contamination_report(none, bench).count() == 0
    assert decontaminate.contamination_report(docs, bench.limit(0)).where("n_hit > 0").count() == 0


def test_no_column_is_lost_to_a_name(spark, docs):
    more = docs.withColumn("contamination", F.lit("mine")).withColumn("_maybe", F.lit(1)).withColumn("_place", F.lit(2)).withColumn("score", F.lit(3)).withColumn("h", F.lit(4))
    bench = spark.createDataFrame([(2, "b C")], "item_id long, text string")
    for mode in ("documents", "spans"):
        found = decontaminate.decontaminate(more, bench, mode)
        assert found.columns == more.columns and found.where("contamination <> 'mine'").count() == 0
    kept = jaccard_join.keep_least(more)
    assert kept.columns == more.columns and kept.where("_maybe <> 1 or _place <> 2 or h <> 4").count() == 0


def test_decontamination_in_several_sets(spark, docs, monkeypatch):
    bench = spark.createDataFrame([(i, f"b c w{i}") for i in range(5)] + [(9, "b c")], "item_id long, text string")
    monkeypatch.setattr(decontaminate, "MAX_WINDOWS", 2)
    assert len(decontaminate.window_sets(bench)) == 3
    assert decontaminate.contamination_report(docs, bench).where("n_hit = 2").count() == 2


# 2


def toxic_corpus(spark, n=400):
    rng = np.random.default_rng(3)
    words = [f"w{i}" for i in range(300)]
    rows, labels = [], []
    for i in range(n):
        text = list(rng.choice(words, 60))
        if i % 4 == 0:
            for k in rng.integers(0, 60, 3):
                text[k] = rng.choice(["idiotic", "disgusting"])
        rows.append((i, " ".join(text)))
        labels.append((i, int(i % 4 == 0)))
    rows.append((n, " ".join([*rng.choice(words, 50), "disgustingg", "idiotiic"])))
    return spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int")


def test_toxicity_learns_and_shares_subwords(spark):
    docs, labels = toxic_corpus(spark)
    model = toxicity.fit(docs, labels)
    got = {r.doc_id: r.score for r in toxicity.toxicity(docs, model).collect()}
    held = [i for i in range(400) if zlib.crc32(str(i).encode()) % 5 == 0]
    assert np.mean([(got[i] >= 0.5) == (i % 4 == 0) for i in held]) > 0.95
    assert got[400] > 0.5  # misspelt words that no training text holds


def test_toxicity_edges(spark, docs, none):
    labels = spark.createDataFrame([(0, 1), (1, None), (99, 1)], "doc_id long, toxic int")
    scores = [r.score for r in toxicity.toxicity(docs, toxicity.fit(docs, labels)).collect()]
    assert len(scores) == len(ODD) + 1 and all(0 <= s <= 1 for s in scores)
    assert toxicity.toxicity(none, toxicity.fit(none, labels.limit(0))).count() == 0
    model = toxicity.train(["good words here", "bad words there"] * 10, [0, 1] * 10)
    assert toxicity.keep_clean(docs.withColumn("score", F.lit(7)), model).columns[-1] == "score"


def test_the_middle_of_long_runs_counts():
    text = "naïve" + "日本語テキスト" * 20 + "x" + "абв" * 30
    data, offs = utf8(pa.array([text, "short words", "", "é" * 16]))
    tokens = features.letter_words(data, offs)
    raw, covered = text.encode(), np.zeros(len(text.encode()), bool)
    for a, b in zip(tokens.starts[: tokens.first[1]], tokens.ends[: tokens.first[1]], strict=True):
        raw[a:b].decode()  # no character is cut
        assert 0 < b - a <= features.LONGEST_WORD + 3
        covered[a:b] = True
    assert covered.all() and tokens.counts[1:].tolist() == [2, 0, 1]
    model = toxicity.train(["good words here"] * 20 + ["idiotic words here"] * 20, [0] * 20 + [1] * 20)
    around = "qwrtzp" * 15
    plain, within = (toxicity.score_slice(model, *utf8(pa.array([t])))[0] for t in (around + "vkjvkjx" + around, around + "idiotic" + around))
    assert within > plain + 0.01
    known = language_id.train(["ababab bababa abab"] * 5 + ["cdcdcd dcdcdc cdcd"] * 5, ["x"] * 5 + ["y"] * 5)
    mixed = "ab" * 12 + "cd" * 100 + "ab" * 12
    assert language_id.predict_slice(known, *utf8(pa.array([mixed])), np.ones(1, bool))[0] == ["y"]


@pytest.mark.parametrize("long", range(6))
def test_one_long_text_never_ends_the_sample(spark, monkeypatch, long):
    monkeypatch.setattr(toxicity, "SAMPLE_BYTES", 100)
    monkeypatch.setattr(language_id, "SAMPLE_BYTES", 100)
    rows = [(i, "long " * 50 if i == long else f"text {i}", "ab"[i % 2], i % 2) for i in range(6)]
    table = spark.createDataFrame(rows, "doc_id long, text string, lang string, toxic int").coalesce(1)
    rest = sorted(t for i, t, *_ in rows if i != long)
    assert sorted(fitting(toxicity.training_sample(table.drop("toxic"), table.select("doc_id", "toxic"), "false").collect(), toxicity.SAMPLE_BYTES)[0]) == rest
    assert sorted(fitting(language_id.training_sample(table, "false").collect(), language_id.SAMPLE_BYTES)[0]) == rest
    one = table.where(f"doc_id = {long}")
    assert len(fitting(language_id.training_sample(one, "false").collect(), language_id.SAMPLE_BYTES)[0]) == 1


# 3


def test_language_model_base_and_tail(spark, docs, real, monkeypatch):
    monkeypatch.setattr(language_model, "CLUSTERED", 100)
    both = real.select("doc_id", "text").unionByName(docs.select((F.col("doc_id") + 100000).alias("doc_id"), "text"))
    rows = both.collect()
    c = collections.Counter()
    for r in rows:
        if r.doc_id is None or zlib.crc32(str(r.doc_id).encode()) % 7 != 2:
            c.update([*spaced(r.text), ""])
    total, distinct = sum(c.values()), len(c)
    want = collections.Counter((r.doc_id, len(spaced(r.text)) + 1, sum(c[w] > 0 for w in [*spaced(r.text), ""]), total, round(sum(np.log10((c[w] + 1) / (total + distinct + 1)) for w in [*spaced(r.text), ""]), 4)) for r in rows)
    full = language_model.score_documents(both)
    got = collections.Counter((r.doc_id, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 4)) for r in full.collect())
    assert got == want
    small = language_model.score_documents(both, head=500).where("doc_id is not null").groupBy("doc_id").agg(F.max("score").alias("b"), F.max("base_score").alias("bb"), F.max("n_known").alias("k"))
    big = full.where("doc_id is not null").groupBy("doc_id").agg(F.max("score").alias("a"), F.max("base_score").alias("aa"), F.max("n_known").alias("kk"))
    assert big.join(small, "doc_id").where("abs(a - b) > 1e-6 or abs(aa - bb) > 1e-6 or k <> kk").count() == 0
    sums = full.where("pmod(crc32(cast(cast(doc_id as string) as binary)), 7) = 2").agg(F.sum("base_score"), F.sum("score")).first()
    assert sums[1] > sums[0]


@pytest.mark.parametrize("head", [60, 1 << 19])
def test_language_model_score_against_brute_force(real, monkeypatch, head):
    monkeypatch.setattr(language_model, "CLUSTERED", 50)
    docs = real.where("doc_id < 80").select("doc_id", "text")
    model, placed = language_model.fit(docs, head=head)
    held = {r.doc_id: spaced(r.text) for r in docs.collect()}
    training = [w for i, w in held.items() if zlib.crc32(str(i).encode()) % 7 != 2]
    c = collections.Counter(w.encode() for words in training for w in words)
    core = sorted(c, key=lambda w: (-c[w], w))[:50]
    of = dict(zip(core, model.look_up(language_model._hash_words(core))[2].tolist(), strict=True))
    of |= {bytes(r.word): r.k for r in placed.collect()}
    assert set(of) == set(c)
    end = max(of.values()) + 1
    tokens, words = collections.Counter(), collections.Counter(of.values())
    for w, n in c.items():
        tokens[of[w]] += n
    moves = np.zeros((end + 1, end + 1))
    for text in training:
        chain = [end, *(of[w.encode()] for w in text), end]
        np.add.at(moves, (chain[:-1], chain[1:]), 1)
    share = (moves.sum(axis=0) + 1) / (moves.sum() + end + 1)
    step = (moves + 0.5 * (end + 1) * share) / (moves.sum(axis=1, keepdims=True) + 0.5 * (end + 1))
    assert np.allclose(step.sum(axis=1), 1)

    def class_of(word):
        if word in of:
            return of[word]
        data, offs = utf8(pa.array([word], pa.binary()))
        return int(model.unseen[language_model.rare_class(Tokens(data, offs, SPACED), np.arange(1))[0]])

    def emission(word, k):
        spare = max(0.6 * words[k], 1.0)
        return (max(c[word] - 0.6, 0) + spare / (words[k] + 1)) / (tokens[k] - 0.6 * words[k] + spare)

    got = {r.doc_id: r.score for r in language_model.score_documents(docs, head=head).collect()}
    for i, text in held.items():
        chain = [end, *(class_of(w.encode()) for w in text), end]
        want = sum(np.log10(step[a, b]) for a, b in zip(chain, chain[1:], strict=False)) + sum(np.log10(emission(w.encode(), k)) for w, k in zip(text, chain[1:-1], strict=True))
        assert abs(got[i] - want) < 1e-6 * max(1, len(text))


def test_language_model_is_a_distribution(none):
    model, _ = language_model.fit(none)
    assert model.total == 0 and abs((10.0**model.transitions).sum(axis=1) - 1).max() < 1e-9


def test_exchange_separates_two_languages():
    rng = np.random.default_rng(1)
    b = np.zeros((20, 20))
    for _ in range(4000):
        side = rng.integers(2) * 10
        b[side + rng.integers(10), side + rng.integers(10)] += 1
    label = language_model.exchange(b, np.full(20, -1), 2)
    assert len(set(label[:10])) == 1 and len(set(label[10:])) == 1 and label[0] != label[10]


def test_rare_words_take_the_classes_of_their_neighbours(spark, monkeypatch):
    """Spellings tell nothing here, only neighbours do; beyond the head as well."""
    monkeypatch.setattr(language_model, "CLUSTERED", 20)
    monkeypatch.setattr(language_model, "CLASSES", 2)
    rng = np.random.default_rng(1)
    rows = []
    for i in range(400):
        side = "ab"[i % 2]
        words = [f"{side}{rng.integers(10)}xx" for _ in range(30)]
        words[15] = f"r{side}{i}xx"
        rows.append((i, " ".join(words)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    for head, most in ((25, "3"), (1000, before)):  # with words that go on in the next batch, and without
        spark.conf.set(key, most)
        model, placed = language_model.fit(docs, "false", head)
        spark.conf.set(key, before)
        assert model.complete == (head == 1000) and model.end_class == 2
        core = model.look_up(language_model._hash_words([f"{s}{k}xx".encode() for s in "ab" for k in range(10)]))[2]
        got = {bytes(r.word).decode(): r.k for r in placed.collect()}
        assert len(set(core[:10])) == len(set(core[10:])) == 1 and core[0] != core[10]
        assert len(got) == 400 and all(k == core[0 if w[1] == "a" else 10] for w, k in got.items())
        assert model.class_words.tolist() == [210, 210, 1] and model.class_tokens[:2].sum() == 12000


# 4


def test_sharding(spark, docs, real, none):
    for table in (docs, real):
        rows = sharding.stratified_shards(table).collect()
        assert len(rows) == table.count()
        by = collections.defaultdict(list)
        for r in rows:
            by[r.shard].append(r.slot)
        assert all(sorted(v) == list(range(len(v))) for v in by.values())
        sizes = [len(by.get(k, [])) for k in range(16)]
        assert max(sizes) - min(sizes) <= 1
    mix = collections.Counter((r.stratum, r.shard) for r in rows)
    n = collections.Counter(r.stratum for r in rows)
    assert all(abs(mix[s, k] - n[s] / 16) <= 2 for s in n for k in range(16))
    assert sharding.stratified_shards(none).count() == 0


def test_sharding_against_brute_force(spark, docs, real):
    for table in (docs.withColumn("rank", F.lit(1)).withColumn("place", F.lit(1)).withColumn("h", F.lit("x")), real):
        rows = []
        for r in table.select("doc_id", "text", "source").collect():
            raw = (r.text or "").encode()
            rows.append((r.doc_id, len(raw) + 1, zlib.crc32(raw), "-" if r.source is None else "+" + r.source))
        frame = spark.createDataFrame(rows, "doc_id long, size long, crc long, stratum string")
        hashed = frame.withColumn("h", F.xxhash64(F.lit(sharding.SEED), "doc_id", "size", "crc")).collect()
        least = lambda x: (x.doc_id is not None, x.doc_id or 0, x.size, x.crc)
        laid = []
        for stratum in {r.stratum for r in hashed}:
            mine = sorted((r for r in hashed if r.stratum == stratum), key=lambda r: (r.h, least(r)))
            laid += [((2 * k + 1) / (2 * len(mine)), stratum, r.h, least(r), r) for k, r in enumerate(mine)]
        laid.sort(key=lambda x: x[:4])
        n, want, slots = len(laid), collections.Counter(), collections.Counter()
        for position, (*_, r) in enumerate(laid):
            shard = position * 16 // n
            want[r.doc_id, r.size, r.crc, "rows", shard, slots[shard], None] += 1
            slots[shard] += 1
        got = sharding.stratified_shards(table).select("doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard").collect()
        assert collections.Counter(tuple(r) for r in got) == want


def test_sharding_buckets_give_plain_ranks(real, monkeypatch):
    def run():
        return sorted((r.doc_id, r.shard, r.slot, r["rank"]) for r in sharding.stratified_shards(real).collect())

    whole = run()
    monkeypatch.setattr(sharding, "BUCKET_ROWS", 7)
    assert run() == whole


# 5


def brute_components(rows, words=4, percent=85):
    sets = []
    for i, text in rows:
        w = spaced(text)
        sets.append((i, {tuple(w[k : k + words]) for k in range(len(w) - words + 1)} if len(w) >= words else {tuple(w)} if w else set()))
    root = {i: i for i, _ in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, (i, s) in enumerate(sets):
        for j, t in sets[:a]:
            if i is not None and j is not None and s and t and 100 * len(s & t) >= percent * len(s | t):
                x, y = find(i), find(j)
                if x != y:
                    root[max(x, y)] = min(x, y)
    return sorted((str(i), len(s), str(find(i) if i is not None else None)) for i, s in sets)


def near_copies(n, seed=5):
    rng = np.random.default_rng(seed)
    rows = []
    for base in range(4):
        words = [f"b{base}w{k}" for k in range(int(rng.integers(8, 160)))]
        for _ in range(n):
            own = list(words)
            for _ in range(int(rng.integers(0, 4))):
                own[int(rng.integers(len(own)))] = f"x{int(rng.integers(1000))}"
            rows.append((len(rows), " ".join(own)))
    return rows


@pytest.mark.parametrize("words,percent", [(4, 85), (5, 80)])
def test_jaccard_join(spark, docs, words, percent, monkeypatch):
    monkeypatch.setattr(jaccard_join, "BLOCK_DOCS", 8)
    rows = near_copies(25) + [(1000 + i if i != 4 else None, t) for i, t in enumerate(ODD)]
    table = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((str(r.doc_id), r.n_shingles, str(r.component_id)) for r in jaccard_join.jaccard_components(table, words, percent).collect())
    assert got == brute_components(rows, words, percent)


def over_passages(seed, n_words=16, n_docs=20, share=11):
    """Documents that each share a passage with the last two, which link but meet only over holders that drop out."""
    rng = np.random.default_rng(seed)
    words = [f"s{seed}w{k}" for k in range(n_words)]
    texts = []
    for d in range(n_docs):
        a = int(rng.integers(0, n_words - share + 1))
        texts.append(" ".join(words[a : a + share] + [f"s{seed}d{d}f{k}" for k in range(int(rng.integers(5, 9)))]))
    return [*texts, " ".join(words), " ".join([*words[:-1], f"s{seed}y"])]


def test_jaccard_join_meets_over_dropped_holders(spark):
    rows = list(enumerate(t for seed in range(40) for t in over_passages(seed)))
    got = sorted((str(r.doc_id), r.n_shingles, str(r.component_id)) for r in jaccard_join.jaccard_components(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert got == brute_components(rows)


def test_signatures_always_meet():
    rng = np.random.default_rng(2)
    for size in (1, 5, 7, 13, 40, 150, 700):
        for _ in range(60):
            a = np.unique(rng.integers(0, 2**63, size, dtype=np.uint64))
            drop = int(rng.integers(0, size // 7 + 1))
            b = np.unique(np.concatenate([a[drop:], rng.integers(0, 2**63, int(rng.integers(0, size // 7 + 1)), dtype=np.uint64)]))
            same = len(np.intersect1d(a, b))
            if 100 * same >= 85 * (len(a) + len(b) - same):
                (x, least_x), (y, least_y) = jaccard_join.signatures(a), jaccard_join.signatures(b)
                common = np.intersect1d(x, y)
                met = False
                for odd in (0, 1):
                    need = max([0, *least_x[x % np.uint64(2) == odd], *least_y[y % np.uint64(2) == odd]])
                    met |= int(np.count_nonzero(common % np.uint64(2) == odd)) >= need > 0
                assert met


def test_keep_least(spark):
    rows = [(i, t, i) for i, t in near_copies(4)]
    table = spark.createDataFrame([*rows, rows[0], (None, "a b", 7), (None, "a b", 7)], "doc_id long, text string, component_id long")
    kept = jaccard_join.keep_least(table).collect()
    want = {c for i, _, c in brute_components([r[:2] for r in rows]) if i == c}
    assert {str(r.doc_id) for r in kept if r.doc_id is not None} == want and sum(r.doc_id is None for r in kept) == 2
    assert len(kept) == len(want) + 2
    assert jaccard_join.keep_least(table.limit(0)).count() == 0


def test_connected(spark):
    links = spark.createDataFrame([(5, 4), (4, 3), (9, 8), (8, 9), (3, 3), (20, 5)], "a long, b long")
    assert {(r.node, r.component) for r in connected(links).collect()} == {(3, 3), (4, 3), (5, 3), (20, 3), (8, 8), (9, 8)}


# 6


def test_token_counts_and_cache(spark, docs, none, tmp_path, monkeypatch):
    import public_tokenizers
    from tokenizers import Tokenizer

    path, cache = public_tokenizers.path("byte_bpe_50k.json"), str(tmp_path / "cache")
    plain = Tokenizer.from_file(path)
    want = collections.Counter((i if i != 4 else None, len((t or "").encode()), len(plain.encode(t or "", add_special_tokens=False).ids)) for i, t in [*enumerate(ODD), (5, ODD[5])])
    for _ in range(2):
        got = collections.Counter((r.doc_id, r.n_bytes, r.n_tokens) for r in token_counts.count_tokens(docs, path, cache).collect())
        assert got == want
    assert spark.read.parquet(cache).count() == len({t or "" for t in ODD})
    assert token_counts.count_tokens(none, path, cache).count() == 0
    # Hits are not encoded again: of a second load only what is new.
    more = docs.unionByName(spark.createDataFrame([(70, "brand new", "en", "s", 1), (71, "brand new", "en", "s", 1), (72, "new too", "en", "s", 1)], docs.schema))
    assert token_counts.extend_cache(docs, path, cache) == (len({t or "" for t in ODD}), 0)
    assert token_counts.extend_cache(more, path, cache) == (len({t or "" for t in ODD}) + 2, 2)
    assert spark.read.parquet(cache).count() == len({t or "" for t in ODD}) + 2
    monkeypatch.setattr(token_counts, "MOST_FILTERED", 0)
    assert collections.Counter((r.doc_id, r.n_bytes, r.n_tokens) for r in token_counts.count_tokens(docs, path, str(tmp_path / "long-way")).collect()) == want
    other = public_tokenizers.path("piece_bpe_32k.model")
    token_counts.count_tokens(docs, other, cache)
    assert spark.read.parquet(cache).select("version").distinct().count() == 2


# 7


def test_language_id(spark, docs, none, real):
    model = language_id.fit(real)
    rows = language_id.identify(real, model).join(real.select("doc_id", "lang"), "doc_id").where("lang is not null").collect()
    held = [r for r in rows if zlib.crc32(str(r.doc_id).encode()) % 3 == 1]
    assert np.mean([r.lang == r.lang_pred for r in held]) > 0.9
    got = [(r.lang_pred, r.score) for r in language_id.identify(spark.createDataFrame([(1, None), (2, ""), (3, "12 !")], "doc_id long, text string"), model).collect()]
    assert got == [("und", 0.0)] * 3
    assert language_id.identify(docs, model).count() == len(ODD) + 1
    assert language_id.identify(docs, language_id.fit(none)).where("lang_pred <> 'und'").count() == 0
    spans = language_id.label_spans(real.limit(5), model).collect()
    assert all(s.spans for s in spans)


def test_forward_backward_against_enumeration():
    from itertools import product

    rng = np.random.default_rng(0)
    emit, move, start = rng.normal(size=(5, 3)), rng.normal(size=(3, 3)), rng.normal(size=3)
    begin, size = np.array([0, 4]), np.array([4, 1])
    gamma, pairs, _, like = language_id.posteriors(emit, begin, size, move, start)
    weight = {p: np.exp(start[p[0]] + sum(emit[t, k] for t, k in enumerate(p)) + sum(move[a, b] for a, b in zip(p, p[1:], strict=False))) for p in product(range(3), repeat=4)}
    z = sum(weight.values())
    for t in range(4):
        for k in range(3):
            assert abs(gamma[t, k] - sum(w for p, w in weight.items() if p[t] == k) / z) < 1e-9
    want = sum(w * sum(a == 0 and b == 1 for a, b in zip(p, p[1:], strict=False)) for p, w in weight.items()) / z
    assert abs(pairs[0, 1] - want) < 1e-9
    assert abs(like - np.log(z) - np.log(np.exp(emit[4] + start).sum())) < 1e-9


def test_pieces_of_a_long_chain_equal_the_whole():
    rng = np.random.default_rng(3)
    emit, move, start = rng.normal(size=(60, 3)), 2 * rng.normal(size=(3, 3)), rng.normal(size=3)
    whole = language_id.posteriors(emit, np.array([0, 20, 23]), np.array([20, 3, 37]), move, start)
    begin, size = np.array([0, 8, 16, 20, 23, 31, 39, 47, 55]), np.array([8, 8, 4, 3, 8, 8, 8, 8, 5])
    parts = language_id.posteriors(emit, begin, size, move, start, np.array([0, 1, 1, 0, 0, 1, 1, 1, 1], bool))
    for a, b in zip(whole, parts, strict=True):
        assert np.allclose(a, b, atol=1e-9)


def test_language_gradients():
    """Counts observed less counts expected are the slope of the likelihood."""
    rng = np.random.default_rng(5)
    emit, move, start = rng.normal(size=(9, 2)), rng.normal(size=(2, 2)), rng.normal(size=2)
    begin, size, gold = np.array([0, 5]), np.array([5, 4]), rng.integers(0, 2, 9)

    def likelihood(move, start):
        total = 0.0
        for b, n in zip(begin, size, strict=True):
            y = gold[b : b + n]
            total += start[y[0]] + emit[np.arange(b, b + n), y].sum() + move[y[:-1], y[1:]].sum()
        return total - language_id.posteriors(emit, begin, size, move, start)[3]

    _, pairs, starts, _ = language_id.posteriors(emit, begin, size, move, start)
    seen = np.zeros((2, 2))
    for b, n in zip(begin, size, strict=True):
        np.add.at(seen, (gold[b : b + n - 1], gold[b + 1 : b + n]), 1)
    for i in range(2):
        for j in range(2):
            d = np.zeros((2, 2))
            d[i, j] = 1e-5
            assert abs((likelihood(move + d, start) - likelihood(move - d, start)) / 2e-5 - (seen - pairs)[i, j]) < 1e-4
        d = np.eye(2)[i] * 1e-5
        assert abs((likelihood(move, start + d) - likelihood(move, start - d)) / 2e-5 - (np.bincount(gold[begin], minlength=2) - starts)[i]) < 1e-4


# 8


def test_warc(spark, tmp_path):
    page = "<p>" + "x" * 200
    rows = [(1, "http://a", page), (2, None, page), (3, "u", None), (4, "u", "short"), (5, "u", "short"), (None, "u", page), (7, "u", "é" * 100), (8, "u\nv", "\r\n\r\n" * 50)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    path = str(tmp_path / "w")
    warc.write_warc(pages.coalesce(1), path)
    got = {r.page_id: r for r in warc.read_warc(spark, path).collect()}
    assert len(got) == len(rows)
    assert got["2"].record_type == "revisit" and got["2"].refers_to == "1" and got["2"].stated_bytes == len(page)
    assert got["1"].record_type == got["4"].record_type == got["5"].record_type == "response"
    for i, _, html in rows:
        r = got[None if i is None else str(i)]
        if r.record_type == "response":
            assert bytes(r.payload) == (html or "").encode()
        assert r.stated_digest == hashlib.sha256((html or "").encode()).hexdigest()
    part = next((tmp_path / "w").glob("part-*"))
    assert gzip.decompress(part.read_bytes()).count(b"WARC/1.1") == len(rows)


def test_warc_splits_and_false_magic(spark, tmp_path):
    """Stored (uncompressed) members hold the magic itself; ranges are far smaller than members."""
    payloads = [bytes([k]) * 50 + warc.MAGIC * (k % 5) + b"tail" * (k * 7) for k in range(60)]
    folder = tmp_path / "v"
    folder.mkdir()
    (folder / "a.warc").write_bytes(b"".join(warc.gzip_member(warc.build_record(k, "u", p, "d", None, "now"), 0) for k, p in enumerate(payloads)))
    before = spark.conf.get("spark.sql.files.maxPartitionBytes")
    for width in ("333", "1000", "100000"):
        spark.conf.set("spark.sql.files.maxPartitionBytes", width)
        spark.conf.set("spark.sql.files.openCostInBytes", "0")
        got = {int(r.page_id): bytes(r.payload) for r in warc.read_warc(spark, str(folder)).collect()}
        assert got == dict(enumerate(payloads))
    spark.conf.set("spark.sql.files.maxPartitionBytes", before)


def test_warc_skips_damage(spark, tmp_path):
    members = [warc.gzip_member(warc.build_record(k, "u", b"p" * 99, "d", None, "now")) for k in range(3)]
    folder = tmp_path / "d"
    folder.mkdir()
    (folder / "a.warc").write_bytes(members[0] + members[1][:-30] + members[2])
    assert sorted(r.page_id for r in warc.read_warc(spark, str(folder)).collect()) == ["0", "2"]


def test_long_records_end_alike():
    member = warc.gzip_member(b"z" * (1 << 24 | 5), 1)
    assert member[-1] == 0 and gzip.decompress(member) == b"z" * (1 << 24 | 5)


# 9


@pytest.fixture(scope="module")
def pieces():
    import public_tokenizers

    return sentencepiece_codec.vocabulary(public_tokenizers.path("piece_bpe_32k.model"))


def test_sentencepiece_equals_library(pieces, real):
    import public_tokenizers
    import sentencepiece

    lib = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))
    texts = [t for t in ODD if "▁" not in (t or "")] + [r.text for r in real.limit(40).collect()]
    data, offs = utf8(pa.array(texts, pa.string()))
    ids, ends = sentencepiece_codec.encode_slice(pieces, data, offs, np.zeros(len(texts)), 1, 0.0)
    assert [ids[a:b].tolist() for a, b in zip(ends, ends[1:], strict=False)] == [lib.encode(t or "") for t in texts]


@pytest.mark.parametrize("rate", [0.0, 0.1, 0.5, 1.0])
def test_sentencepiece_is_lossless(pieces, rate, real):
    texts = ODD + [r.text for r in real.limit(20).collect()]
    data, offs = utf8(pa.array(texts, pa.string()))
    ids, ends = sentencepiece_codec.encode_slice(pieces, data, offs, np.arange(len(texts)) % 4, 9, rate)
    back, spans = sentencepiece_codec.decode_slice(pieces, ids, ends)
    assert back.tobytes() == data.tobytes() and (spans == offs).all()


def test_dropout_draws_for_every_occurrence(pieces):
    data, offs = utf8(pa.array([" ".join(["understanding"] * 400)] * 2, pa.string()))
    ids, ends = sentencepiece_codec.encode_slice(pieces, data, offs, np.array([1, 2]), 9, 0.1)
    again, _ = sentencepiece_codec.encode_slice(pieces, data, offs, np.array([1, 2]), 9, 0.1)
    assert (ids == again).all() and ids[: ends[1]].tolist() != ids[ends[1] :].tolist()
    spelt = [pieces.bytes[i] for i in ids[: ends[1]].tolist()]
    words, one = set(), []
    for p in spelt:
        if p.startswith(b" ") and one:
            words.add(tuple(one))
            one = []
        one.append(p)
    assert len(words) > 20


def test_sentencepiece_matrices_equal_heap(pieces, real):
    data, offs = utf8(pa.array([r.text for r in real.limit(10).collect()], pa.string()))
    spelt, _, starts = sentencepiece_codec.units(data, offs)
    ends = np.append(starts[1:], len(spelt))
    short = np.flatnonzero(ends - starts < 30)[:400]
    keys = np.arange(len(short), dtype=np.uint64) * np.uint64(7919)
    many, n = sentencepiece_codec.segment(pieces, spelt, starts[short], ends[short], keys, 0.4)
    before, sentencepiece_codec.LONG = sentencepiece_codec.LONG, 0
    heap = []
    try:
        for i in range(len(short)):
            text = spelt[starts[short[i]] : ends[short[i]]].tobytes().decode()
            symbols = [pieces.ids.get(c.encode(), -1) for c in text]
            heap.append(sentencepiece_codec.merge_one(pieces, symbols, int(keys[i]), 0.4) if -1 not in symbols else None)
    finally:
        sentencepiece_codec.LONG = before
    at = np.concatenate([[0], np.cumsum(n)])
    assert all(h is None or h == many[a:b].tolist() for h, a, b in zip(heap, at, at[1:], strict=False))


def test_sentencepiece_frames(docs, none):
    import public_tokenizers

    path = public_tokenizers.path("piece_bpe_32k.model")
    back = sentencepiece_codec.decode_pieces(sentencepiece_codec.encode_pieces(docs, path), path).collect()
    assert collections.Counter((r.doc_id, r.decoded) for r in back) == collections.Counter((i if i != 4 else None, t or "") for i, t in [*enumerate(ODD), (5, ODD[5])])
    assert sentencepiece_codec.piece_digests(docs, path).where("not lossless").count() == 0
    assert sentencepiece_codec.piece_digests(none, path).count() == 0


# 10


def test_telephony_tables():
    assert media.EXPAND["mulaw"][[0x00, 0x80, 0xFF, 0x7F]].tolist() == [-32124, 32124, 0, 0]
    assert media.EXPAND["alaw"][[0xD5, 0x55, 0xAA, 0x2A]].tolist() == [8, -8, 32256, -32256]


def test_adpcm_against_a_plain_decoder():
    rng = np.random.default_rng(4)
    blocks = rng.integers(0, 256, (5, 64), dtype=np.uint8)
    for block, got in zip(blocks, media.decode_adpcm(blocks), strict=True):
        value, index = int(block[:2].view("<i2")[0]), min(int(block[2]), 88)
        out = [value]
        for b in block[4:].tolist():
            for nibble in (b & 15, b >> 4):
                step = int(media.STEPS[index])
                move = step // 8 + (step if nibble & 4 else 0) + (step // 2 if nibble & 2 else 0) + (step // 4 if nibble & 1 else 0)
                value = max(-32768, min(32767, value - move if nibble & 8 else value + move))
                index = max(0, min(88, index + int(media.INDEX_MOVES[nibble & 7])))
                out.append(value)
        assert got.tolist() == out


def plain_feature(codec, payload):
    """Samples, peak, mean, zero crossings and the resampled PCM's CRC, sample by sample."""
    if codec == "ima_adpcm":
        pcm = [int(x) for block in range(0, len(payload), 576) for x in media.decode_adpcm(np.frombuffer(payload[block : block + 576], np.uint8).reshape(1, -1))[0]]
    else:
        pcm = [int(media.EXPAND[codec][b]) for b in payload]
    # Twice the rate: every sample, then the middle of it and its neighbour, rounded down; the last one is repeated.
    twice = [y for i, x in enumerate(pcm) for y in (x, (x + pcm[min(i + 1, len(pcm) - 1)]) // 2)]
    crossings = sum((a < 0) != (b < 0) for a, b in zip(pcm, pcm[1:], strict=False))
    packed = b"".join(x.to_bytes(2, "little", signed=True) for x in twice)
    return f"{codec};n={len(pcm)};peak={max(map(abs, pcm))};mean={sum(map(abs, pcm)) // len(pcm)};zc={crossings};pcm16000={zlib.crc32(packed):08x}"


def test_media(spark, docs, none, tmp_path):
    media.write_media(docs, str(tmp_path / "m"))
    stored = media.read_media(spark, str(tmp_path / "m"))
    rows = media.media_summary(stored).collect()
    blobs = {hashlib.sha256(bytes(r.media)).hexdigest(): bytes(r.media) for r in stored.collect()}
    for r in rows:
        codec, _, _, payload = media.read_wav(blobs[r.media_sha256])
        assert r.media_bytes == len(blobs[r.media_sha256]) and r.payload_bytes == len(payload) and r.feature == plain_feature(codec, payload)
    media.write_pcm(stored, str(tmp_path / "pcm"))
    assert spark.read.parquet(str(tmp_path / "pcm")).where("rate = 16000 and length(pcm) > 0").count() == len(rows)
    got = collections.Counter((r.doc_id, r.n_bytes, r.payload_sha256, r.tail_crc32) for r in rows)
    want = collections.Counter()
    for i, t in [*enumerate(ODD), (5, ODD[5])]:
        raw = (t or "").encode()
        payload = raw + b"\xff" * (max(576, -(-len(raw) // 576) * 576) - len(raw))
        want[i if i != 4 else None, len(raw), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:])] += 1
    assert got == want
    media.write_media(none, str(tmp_path / "none"))
    assert media.media_summary(media.read_media(spark, str(tmp_path / "none"))).count() == 0
    kept = media.decode_media(media.store_media(docs.withColumn("audio", F.lit(1)), column="blob"), "blob", into="sound")
    assert kept.columns == [*docs.columns, "audio", "blob", "sound"]
    for codec in media.FORMATS:
        back = media.decode_media(media.store_media(docs, codec)).select("text", "audio.*").collect()
        assert all(bytes(r.payload).startswith((r.text or "").encode()) and r.codec == codec for r in back)
    assert media.read_wav(b"no wav at all") is None


# Pipeline


def test_pipeline_stages(spark, sf):
    pipeline = pytest.importorskip("corpus_pipeline")
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, before = docs.columns, docs
    for name, stage in pipeline.STAGES:
        after = pipeline.stored(stage(spark, before, sf), name)
        if name != "sentencepiece":
            assert after.columns == columns and after.exceptAll(before).count() == 0
        if name == "near_duplicates":
            want = {i for i, _, c in brute_components([(r.doc_id, r.text) for r in before.collect()], 5, 80) if i == c}
            assert {str(r.doc_id) for r in after.collect()} == want
        if name == "decontamination":
            items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
            rows = before.collect()
            clean = {r.doc_id for r, (_, hit, _) in zip(rows, brute_hits([r.text for r in rows], items), strict=True) if not hit}
            assert {r.doc_id for r in after.collect()} == clean
        before = after
    assert before.count() > 0


def test_pipeline_on_odd_rows(spark, sf, docs, none):
    pipeline = pytest.importorskip("corpus_pipeline")
    odd = docs.withColumn("score", F.lit(1)).withColumn("node", F.lit("x"))
    before = odd
    for name, stage in pipeline.STAGES:
        after = pipeline.stored(stage(spark, before, sf), name)
        if name != "sentencepiece":
            assert after.columns == odd.columns
            assert after.where("doc_id is null").count() == 1  # its text is a word
        before = after
    assert before.count() > 0
    for name, stage in pipeline.STAGES:
        assert stage(spark, none, sf).count() == 0
