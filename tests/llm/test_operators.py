"""Each operator against brute force on small tables, and its defined results for awkward rows."""

import hashlib
import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from sparse_topics.llm import common, components, decontaminate, langid, media, mixing, quality, resemblance, sharding, simhash, substrings, toxicity, urls

AWKWARD = "doc_id long, text string, lang string, source string, size long, shard int, key string, row string"


@pytest.fixture(scope="module")
def awkward(spark):
    long = " ".join(f"w{i % 977}" for i in range(30_000))
    rows = [(1, None, None, None), (2, "", "en", "b"), (3, "one", "en", "b"), (4, "two words", None, None), (4, "two words", None, None), (None, "no id here at all", "en", "a"), (6, long, "en", "a"), (7, long, "fr", "a"), (8, "...", "fr", "z"), (9, "é" * 60, "fr", "z")]
    return spark.createDataFrame([(*r, 5, 6, "k", "r") for r in rows], AWKWARD)


@pytest.fixture(scope="module")
def nothing(awkward):
    return awkward.where("1 = 0")


def words(text):
    return (text or "").encode().lower().split()


def test_word_count_and_words(spark):
    df = spark.createDataFrame([("a\u00a0b  C\n\x0bd",), (None,), ("",)], "text string")
    got = df.select(common.word_count(F.col("text")).alias("n"), common.words_of(F.col("text")).alias("w")).collect()
    assert [(r.n, r.w) for r in got] == [(3, ["a\u00a0b", "c", "d"]), (0, []), (0, [])]


# ---- mixing -----------------------------------------------------------------------------------------------------


def water(sizes, weights, cap=3.0):
    total, full, out = sum(sizes.values()), set(), {}
    while True:
        rest = total - sum(cap * sizes[s] for s in full)
        w = sum(weights[s] for s in sizes if s not in full)
        over = {s for s in sizes if s not in full and rest * weights[s] / w > cap * sizes[s]}
        if not over:
            return {s: cap * sizes[s] if s in full else rest * weights[s] / w for s in sizes}
        full |= over


def test_mix_targets_and_budgets(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    rows = mixing.mix(docs).collect()
    sizes, taken, largest, target = Counter(), Counter(), Counter(), {}
    source = {r.doc_id: r.source for r in docs.select("doc_id", "source").collect()}
    for r in rows:
        sizes[source[r.doc_id]] += r["size"]
        taken[source[r.doc_id]] += r.taken
        target[source[r.doc_id]] = r.target
        largest[source[r.doc_id]] = max(r["size"], largest[source[r.doc_id]])
        assert r.taken <= 3 * r["size"] and r.taken == r.copies * r["size"]
    order = sorted(sizes)
    want = water(sizes, {s: i % 3 + 1 for i, s in enumerate(order)})
    for s in order:
        assert target[s] == pytest.approx(want[s])
        assert abs(taken[s] - target[s]) <= max(0.05 * target[s], largest[s] / 2)
    assert sorted(map(tuple, mixing.mix(docs).collect())) == sorted(map(tuple, rows))


def test_mix_caps_and_reshares(spark):
    docs = spark.createDataFrame([(i, "x " * 10, "en", s) for i, s in enumerate(["a"] * 90 + ["b"] * 5 + ["c"] * 5)], "doc_id long, text string, lang string, source string")
    got = {r.key: r for r in mixing.targets(mixing.sized(docs)).collect()}
    want = water({"sa": 900, "sb": 50, "sc": 50}, {"sa": 1, "sb": 2, "sc": 3})
    assert {k: got[k].target for k in got} == pytest.approx(want)


def test_mix_awkward(awkward, nothing):
    rows = mixing.mix(awkward).collect()
    assert len(rows) == awkward.count() and all(r["size"] >= 0 for r in rows)
    back = mixing.mix_rows(awkward)
    assert back.columns == awkward.columns
    assert back.count() == sum(r.copies for r in rows)
    assert mixing.mix(nothing).count() == 0 and mixing.mix_rows(nothing).count() == 0


def test_mix_splits_a_source_without_ids(spark):
    rows = [(None, f"word{i} " * 10, "en", "a") for i in range(400)] + [(i, "x " * 10, "en", "b") for i in range(100)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    got = mixing.mix(docs).where("doc_id is null").collect()
    assert abs(sum(r.taken for r in got) - got[0].target) <= 10


# ---- sharding ---------------------------------------------------------------------------------------------------


def test_shards_are_even_gapless_and_mixed(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    rows = sharding.shard_documents(docs).collect()
    by = defaultdict(list)
    for r in rows:
        by[r.shard].append(r.slot)
    assert sorted(by) == list(range(8)) and max(map(len, by.values())) - min(map(len, by.values())) <= 1
    assert all(sorted(v) == list(range(len(v))) for v in by.values())
    source = {r.doc_id: (r.source, r.text) for r in docs.collect()}
    mix = Counter((source[r.doc_id][0], r.shard) for r in rows)
    whole = Counter(s for s, _ in source.values())
    assert all(abs(mix[s, k] - whole[s] / 8) <= 2 for s in whole for k in range(8))
    for r in rows:
        text = source[r.doc_id][1].encode()
        assert (r["size"], r.text_crc32, r.law, r.grown_shard) == (len(text) + 1, zlib.crc32(text), "rows", None)


def test_shard_rows_keeps_every_row(spark, awkward, nothing):
    out = sharding.shard_rows(awkward, shards=3)
    rows = out.collect()
    assert Counter((r.doc_id, r.text) for r in rows) == Counter((r.doc_id, r.text) for r in awkward.collect())
    assert sorted((r.shard, r.slot) for r in rows) == [(s, i) for s, n in ((0, 4), (1, 3), (2, 3)) for i in range(n)]
    assert sharding.shard_rows(nothing, shards=3).count() == 0 and sharding.shard_documents(nothing).count() == 0


# ---- URL filter -------------------------------------------------------------------------------------------------


def test_url_rules(spark):
    pages = spark.createDataFrame([(1, "https://A.Example.org/es/x?q"), (2, "http://example.org/en/17#t"), (3, "x://notexample.com/de/"), (4, None), (5, "no scheme"), (6, "h://com"), (7, "h://b.com/fr/1"), (7, "h://b.com/fr/1"), (8, "h://org")], "page_id long, url string")
    rules = urls.rule_table(spark, urls.RULES)
    got = sorted(((r.page_id, r.host, r.path, r.rule, r.verdict) for r in urls.filter_urls(pages, rules).collect()), key=lambda r: r[0])
    assert got == [
        (1, "a.example.org", "/es/x", "example.org/es/", "block"), (2, "example.org", "/en/17", "example.org/en/1", "block"), (3, "notexample.com", "/de/", "com/de/", "block"),
        (4, "", "", None, "allow"), (5, "", "", None, "allow"), (6, "com", "", None, "allow"), (7, "b.com", "/fr/1", "com/fr/", "allow"), (7, "b.com", "/fr/1", "com/fr/", "allow"), (8, "org", "", None, "allow"),
    ]
    clash = spark.createDataFrame([(1, "https://x.org/" + "a" * 200_000, "h", "p", "r", 5, "b", "s", "d")], "page_id long, url string, host string, path string, rule string, row int, h string, short string, digest string")
    assert [(r.host, len(r.path), r.rule) for r in urls.filter_urls(clash, rules).collect()] == [("x.org", 200_001, "org/")]
    assert urls.filter_urls(pages, rules.limit(0)).where("rule is not null").count() == 0
    assert urls.filter_urls(pages.limit(0), rules).count() == 0


# ---- SimHash ----------------------------------------------------------------------------------------------------


def slow_fingerprint(text):
    w = words(text)
    if not w:
        return 0
    grams = [b" ".join(w[i : i + 3]) for i in range(max(1, len(w) - 2))]
    hashes = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_fingerprint():
    rng = random.Random(1)
    for n in (0, 1, 2, 3, 4, 50, 400):
        text = " ".join(rng.choice(["ab", "Ça", "X", "yz\u00a0q"]) for _ in range(n))
        assert simhash.fingerprint(text) == slow_fingerprint(text)
    assert simhash.fingerprint(None) == 0


def brute_classes(values, most):
    root = {v: v for v in values}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ordered = sorted(values)
    for i, a in enumerate(ordered):
        for b in ordered[:i]:
            if (a ^ b).bit_count() <= most:
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {v: find(v) for v in values}


def planted(seed, n=150):
    rng = random.Random(seed)
    out = set()
    for _ in range(n):
        v = rng.getrandbits(64)
        out.add(v)
        for _ in range(rng.randrange(5)):
            for _ in range(rng.randrange(1, 4)):
                v ^= 1 << rng.randrange(64)
            out.add(v)
    return out


def test_pigeonring_links_lose_nothing(spark):
    values = planted(3)
    signed = np.array(sorted(values), np.uint64).view(np.int64).tolist()
    edges = simhash.links(spark.createDataFrame([(v,) for v in signed], "fp long"))
    roots = {r.node: r.root for r in components.components(edges).collect()}
    want = brute_classes(values, 2)
    groups = defaultdict(set)
    for v in signed:
        groups[roots.get(v, v)].add(v & (1 << 64) - 1)
    expected = defaultdict(set)
    for v, r in want.items():
        expected[r].add(v)
    assert sorted(map(sorted, groups.values())) == sorted(map(sorted, expected.values()))


def test_long_runs_agree_with_short_ones(monkeypatch):
    rng = random.Random(5)
    for start in (0, 3, 15):
        mask = int(simhash._prefix_mask(start))
        base = rng.getrandbits(64)
        values = sorted({(base & mask) | (v & ~mask & (1 << 64) - 1) for v in planted(start, 40)} | {base ^ (1 << b) ^ (1 << c) for b in range(64) if not mask >> b & 1 for c in range(b) if not mask >> c & 1})[:300]
        fps = np.array(values, np.uint64)
        monkeypatch.setattr(simhash, "BLOCK_RUN", 1 << 20)
        a, b = simhash.link_run(fps, start)
        monkeypatch.setattr(simhash, "BLOCK_RUN", 0)
        c, d = simhash.link_run(fps, start)
        full = brute_classes(set(values), 2)
        assert {(int(x), int(y)) for x, y in zip(c, d)} == {(v, r) for v, r in full.items() if v != r}
        for x, y in zip(a, b):  # the chain test leaves pairs to other starts, and links nothing else
            assert full[int(x)] == full[int(y)]


def test_near_duplicates_whole(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    rows = simhash.near_duplicates(docs).collect()
    texts = {r.doc_id: r.text for r in docs.collect()}
    fps = {i: slow_fingerprint(t) for i, t in texts.items()}
    classes, least = brute_classes(set(fps.values()), 2), {}
    for i, f in fps.items():
        least[classes[f]] = min(i, least.get(classes[f], i))
    assert {(r.doc_id, r.fingerprint, r.component_id) for r in rows} == {(i, f"{f:016x}", least[classes[f]]) for i, f in fps.items()}
    kept = simhash.keep_one(docs)
    assert sorted(r.doc_id for r in kept.collect()) == sorted(set(least.values())) and kept.columns == docs.columns


def test_near_duplicates_awkward(awkward, nothing):
    rows = simhash.near_duplicates(awkward).collect()
    assert len(rows) == awkward.count()
    assert {r.component_id for r in rows if r.fingerprint == "0" * 16} == {1}
    assert len(simhash.keep_one(awkward).collect()) == len({r.component_id for r in rows})
    assert simhash.near_duplicates(nothing).count() == 0 and simhash.keep_one(nothing).count() == 0


@pytest.mark.parametrize("hot_run", [0, 3])
def test_hot_runs_are_dealt_again(spark, hot_run):
    rng = random.Random(hot_run)
    base = rng.getrandbits(64)
    values = planted(9, 60) | {base ^ sum(1 << b for b in rng.sample(range(40), rng.randrange(1, 6))) for _ in range(400)}
    signed = np.array(sorted(values), np.uint64).view(np.int64).tolist()
    edges = simhash.links(spark.createDataFrame([(v,) for v in signed], "fp long"), hot_run)
    roots = {r.node: r.root for r in components.components(edges).collect()}
    want, got = defaultdict(set), defaultdict(set)
    for v, r in brute_classes(values, 2).items():
        want[r].add(v)
    for v in signed:
        got[roots.get(v, v)].add(v & (1 << 64) - 1)
    assert sorted(map(sorted, got.values())) == sorted(map(sorted, want.values()))


def test_components(spark):
    edges = [(i, i + 1) for i in range(60)] + [(200, i) for i in range(100, 200)] + [(300, 300), (7, 7)]
    roots = {r.node: r.root for r in components.components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert roots == {i: 0 for i in range(1, 61)} | {i: 100 for i in range(101, 201)}


# ---- resemblance ------------------------------------------------------------------------------------------------


def test_resembling_pairs_are_all_found(spark, tiny):
    rng = random.Random(11)
    base = [[f"w{rng.randrange(5000)}" for _ in range(rng.randrange(6, 120))] for _ in range(60)]
    passage = [f"common{i}" for i in range(30)]
    texts = [" ".join(w) for w in base] + ["", " ", "one", "ONE", "two words"]
    for w in base:
        for _ in range(3):
            v = w.copy()
            for _ in range(rng.randrange(3)):
                v[rng.randrange(len(v))] = f"x{rng.randrange(9)}"
            texts.append(" ".join(v + passage[: rng.choice([0, 2, 30])]))
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    docs = docs.unionByName(spark.read.parquet(f"{tiny}/documents.parquet").select((F.col("doc_id") + 10_000).alias("doc_id"), "text"))
    grams = {}
    for r in docs.collect():
        w = words(r.text)
        k = min(5, len(w))
        grams[r.doc_id] = frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if w else frozenset()
    root = {i: i for i in grams}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids, missed = sorted(grams), 0
    for i, a in enumerate(ids):
        for b in ids[:i]:
            x, y = grams[a], grams[b]
            if x == y or (x and y and len(x & y) / len(x | y) >= 0.8):
                missed += x != y
                root[max(find(a), find(b))] = min(find(a), find(b))
    assert missed > 50
    kept = resemblance.keep_one(docs)
    assert sorted(r.doc_id for r in kept.collect()) == [i for i in ids if find(i) == i] and kept.columns == docs.columns


def test_nearest_pairs_of_fingerprints(spark):
    """Each fingerprint with a partner before it in a run gets its nearest one; pairs beyond the distance never come."""
    rng = random.Random(4)
    values = []
    for _ in range(40):
        base = rng.getrandbits(64)
        values += [base] + [base ^ sum(1 << b for b in rng.sample(range(64), rng.randrange(0, 8))) for _ in range(4)]
    rows = [(m, int(np.uint64(v).view(np.int64))) for m, v in enumerate(values)]
    for run in (simhash.BLOCK_RUN, 2):
        got = {tuple(r) for r in simhash.nearest(spark.createDataFrame(rows, "mark long, fp long"), 5, run).collect()}
        far = {(i, j): (values[i] ^ values[j]).bit_count() for j in range(len(values)) for i in range(j)}
        assert got and all(far[p] <= 5 for p in got) and len(got) <= 16 * len(values)
        if run > 2:
            linked = {m for p in got for m in p}
            assert linked >= {max(p, key=lambda m: (rows[m][1], m)) for p, d in far.items() if d <= 5}
    with pytest.raises(ValueError):
        simhash.nearest(spark.createDataFrame(rows, "mark long, fp long"), 16)


def test_a_group_of_near_copies_is_not_paired(spark, monkeypatch):
    """Near copies of one text, most of them under the share with each other, and texts around one passage: candidates stay
    in proportion to the rows, the first ones come from the fingerprints, and no component is lost."""
    rng = random.Random(6)
    base, passage, texts = [f"b{i}" for i in range(120)], [f"p{i}" for i in range(40)], []
    for _ in range(150):
        w = base.copy()
        for _ in range(rng.randrange(1, 5)):
            w[rng.randrange(len(w))] = f"x{rng.randrange(10**6)}"
        texts.append(" ".join(w))
    texts += [" ".join(passage + [f"y{rng.randrange(10**6)}" for _ in range(40)]) for _ in range(150)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    rounds, whole = [], resemblance._verified

    def counted(pairs, *more):
        rounds.append(pairs.distinct().count())
        return whole(pairs, *more)

    searched = []
    monkeypatch.setattr(resemblance, "nearest", lambda marked, bits: searched.append(bits) or simhash.nearest(marked, bits))
    monkeypatch.setattr(resemblance, "_verified", counted)
    kept = sorted(r.doc_id for r in resemblance.keep_one(docs).collect())
    assert searched == [resemblance.BITS] and rounds[0] > 0 and max(rounds) <= 8 * len(texts)
    sets = [set(zip(*[w[i:] for i in range(5)], strict=False)) for w in map(str.split, texts)]
    root = list(range(len(texts)))
    for j in range(len(texts)):
        for i in range(j):
            if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]) and root[i] != root[j]:
                a, b = root[i], root[j]
                root = [min(a, b) if r in (a, b) else r for r in root]
    assert kept == [i for i, r in enumerate(root) if i == r]


def test_keys_that_are_left_out_lose_no_pair(spark):
    """Every resembling pair still meets under a key that fits it, and sets that share many keys meet few times."""
    rng, sets = random.Random(8), []
    for _ in range(60):
        base = [rng.randrange(1 << 62) for _ in range(rng.randrange(1, 120))]
        sets.append(base)
        for _ in range(4):
            cut = rng.choice([0.0, 0.05, 0.1, 0.12, 0.2, 0.3])
            sets.append([x for x in base if rng.random() >= cut] + [rng.randrange(1 << 62) for _ in range(rng.randrange(1 + len(base) // 10))])
    passage = [rng.randrange(1 << 10) for _ in range(40)]  # first in the order, in sets that resemble no other
    sets += [passage + [rng.randrange(1 << 62) for _ in range(60)] for _ in range(30)]
    sets = [sorted(set(s)) for s in {tuple(s) for s in sets if s}]
    share = resemblance.SHARE
    rows = [(i, len(s), p, k, i) for i, s in enumerate(sets) for p, k in enumerate(s[: resemblance.prefix_length(len(s), share)])]
    keys = spark.createDataFrame(rows, "fp long, n int, pos int, key long, root long")
    left = resemblance._first_keys(resemblance._apart(keys, share, 0)).collect()
    assert len({(r.fp, r.key) for r in left}) == len(left) and {(r.fp, r.n, r.pos, r.key, r.root) for r in left} <= set(rows)
    by_key = {}
    for r in left:
        by_key.setdefault(r.key, []).append(r)
    met = set()
    for group in by_key.values():
        for a in group:
            met |= {(a.fp, b.fp) for b in group if a.fp < b.fp and min(a.n - a.pos, b.n - b.pos) >= share / (1 + share) * (a.n + b.n) - 1e-6}
    want = {(i, j) for j in range(len(sets)) for i in range(j) if len(set(sets[i]) & set(sets[j])) >= share * len(set(sets[i]) | set(sets[j]))}
    assert len(want) > 50 and want <= met
    of_passage = [r for r in left if r.key < 1 << 10]
    assert 0 < len(of_passage) <= 45 < 500 < sum(k < 1 << 10 for *_, k, _ in rows)


def test_sketches_go_with_few_keys(spark, monkeypatch):
    """Texts that share half of their words with one other, and resemble none: a sketch is sent about once for each partner
    and not once for each common key."""
    rng, texts = random.Random(9), []
    for i in range(100):
        common = [f"c{i}x{j}" for j in range(100)]
        texts += [" ".join(common + [f"y{rng.randrange(10**9)}" for _ in range(60)]) for _ in range(2)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    tables, write = {}, resemblance.write_table

    def kept(df, name):
        if name in ("resemblance-keys", "resemblance-last"):
            tables.setdefault(name, []).append(df.count())
        return write(df, name)

    monkeypatch.setattr(resemblance, "write_table", kept)
    assert resemblance.keep_one(docs).count() == len(texts)
    keys, (last,) = tables["resemblance-keys"][-1], tables["resemblance-last"]
    assert 0 < last <= len(texts) < 3 * len(texts) < keys


def test_resemblance_awkward(awkward, nothing):
    kept = resemblance.keep_one(awkward).collect()
    assert len(kept) == len({tuple(words(r.text)) for r in awkward.collect()})
    assert resemblance.keep_one(nothing).count() == 0


# ---- decontamination --------------------------------------------------------------------------------------------


def test_leaks_against_brute_force(spark, tiny):
    docs, bench = spark.read.parquet(f"{tiny}/documents.parquet"), spark.read.parquet(f"{tiny}/benchmark.parquet")
    some = bench.limit(20).collect()
    short = [(900, "Th"), (901, " "), (902, None), (903, "the of is")]
    cut = [(1000 + r.item_id, " ".join(r.text.split()[3:]) + " tail of other words") for r in some]
    more = spark.createDataFrame([(r.item_id, r.text) for r in some] + short + cut, "item_id long, text string")
    rows = decontaminate.find_leaks(docs, more).collect()
    want = set()
    for item in more.collect():
        w = words(item.text)
        k = min(5, len(w))
        grams = {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if w else set()
        for d in docs.collect():
            v = words(d.text)
            n = len(grams & {tuple(v[i : i + k]) for i in range(len(v) - k + 1)})
            if grams and n >= 0.8 * len(grams):
                want.add((d.doc_id, item.item_id, len(grams), n))
    assert {(r.doc_id, r.item_id, r.shingles, r.found) for r in rows} == want and len(want) > 10
    left = decontaminate.drop_leaks(docs, more)
    assert {r.doc_id for r in left.collect()} == {r.doc_id for r in docs.collect()} - {w[0] for w in want} and left.columns == docs.columns


@pytest.mark.parametrize("share", [0.2, 0.5, 0.8, 1.0])
def test_no_leak_is_lost_at_any_share(spark, share):
    rng = random.Random(int(share * 10))
    items = [(i, " ".join(f"i{i}w{j}" for j in range(n))) for i, n in enumerate([5, 6, 9, 12, 12, 20, 33, 64])]
    docs = []
    for d in range(160):
        parts = []
        for _ in range(rng.randrange(3)):
            w = rng.choice(items)[1].split()
            a = rng.randrange(len(w) - 4)
            parts += w[a : rng.randrange(a + 5, len(w) + 1)] + [f"x{rng.randrange(99)}" for _ in range(rng.randrange(4))]
        docs.append((d, " ".join([f"y{rng.randrange(999)}" for _ in range(rng.randrange(60))] + parts)))
    grams = lambda t: {tuple(w[i : i + 5]) for w in [t.split()] for i in range(len(w) - 4)}
    want = {(d, i, n, f) for d, t in docs for i, item in items for n, f in [(len(grams(item)), len(grams(item) & grams(t)))] if f >= share * n}
    rows = decontaminate.find_leaks(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"), share=share).collect()
    assert {(r.doc_id, r.item_id, r.shingles, r.found) for r in rows} == want and len(want) > 10


def test_items_of_equal_or_no_id_are_kept_apart(spark):
    docs = spark.createDataFrame([(1, "a b c d e f"), (2, "g h i j k l"), (3, "m n o p q r s")], "doc_id long, text string")
    bench = spark.createDataFrame([(7, "a b c d e f"), (7, "g h i j k l"), (None, "m n o p q r"), (None, "s t u v w x"), (7, "a b c d e f")], "item_id long, text string")
    rows = decontaminate.find_leaks(docs, bench).collect()
    assert sorted((r.doc_id, r.item_id or -1, r.shingles) for r in rows) == [(1, 7, 2), (2, 7, 2), (3, -1, 2)]


def test_leaks_awkward(spark, awkward, nothing):
    bench = spark.createDataFrame([(1, "no id here at all")], "item_id long, text string")
    assert [(r.doc_id, r.item_id) for r in decontaminate.find_leaks(awkward, bench).collect()] == [(None, 1)]
    assert decontaminate.drop_leaks(awkward, bench).count() == awkward.count() - 1
    assert decontaminate.find_leaks(nothing, bench).count() == 0
    assert decontaminate.find_leaks(awkward, bench.limit(0)).count() == 0 and decontaminate.drop_leaks(awkward, bench.limit(0)).count() == awkward.count()


# ---- repeated substrings ----------------------------------------------------------------------------------------


def slow_removed(docs, length=50):
    first = {}
    for i, t in docs:
        for p in range(len(t) - length + 1):
            w = t[p : p + length]
            first[w] = min(first.get(w, i), i)
    out = []
    for i, t in docs:
        gone = bytearray(len(t))
        for p in range(len(t) - length + 1):
            if first[t[p : p + length]] < i:
                gone[p : p + length] = b"\1" * length
        out.append((i, len(t), sum(gone), hashlib.sha256(bytes(b for b, g in zip(t, gone) if not g)).hexdigest()))
    return sorted(out)


@pytest.mark.parametrize("hot_pages", [substrings.HOT_PAGES, 0])
def test_substrings_against_brute_force(spark, monkeypatch, hot_pages):
    rng = random.Random(hot_pages)
    parts = ["".join(rng.choice("abcé ") for _ in range(rng.randrange(30, 140))) for _ in range(12)]
    rows = []
    for i in range(120):
        text = "".join(rng.choice(parts)[rng.randrange(20) :] + "".join(rng.choice("xyz ") for _ in range(rng.randrange(12))) for _ in range(rng.randrange(8)))
        rows.append((rng.randrange(90), text))
    rows += [(200, "ab" * 400), (201, "ab" * 300), (202, None), (203, "q" * 49), (204, "q" * 50), (205, "q" * 51)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    monkeypatch.setattr(substrings, "PAGE_BYTES", 2000)
    got = substrings.remove_repeats(df, hot_pages=hot_pages).collect()
    want = slow_removed([(i, (t or "").encode()) for i, t in rows])
    assert sorted((r.doc_id, r.n_bytes, r.n_removed, hashlib.sha256(r.kept).hexdigest()) for r in got) == want
    assert all(sum(s.stop - s.start for s in r.spans) == r.n_removed for r in got)


def test_substrings_awkward(awkward, nothing):
    got = substrings.remove_repeats(awkward).collect()
    assert len(got) == awkward.count()
    by = {r.doc_id: r for r in got}
    assert by[7].n_removed == by[7].n_bytes == by[6].n_bytes and by[6].n_removed == 0
    assert substrings.remove_repeats(nothing).count() == 0


def test_equal_windows():
    rng = random.Random(2)
    t = np.frombuffer(bytes(rng.choice(b"abc") for _ in range(4000)) + b"\xff", np.uint8)
    order, interval = substrings.equal_windows(t, 12)
    raw = t.tobytes()
    keys = [raw[i : i + 12] for i in order if i + 12 <= len(raw)]
    numbers = [g for i, g in zip(order, interval) if i + 12 <= len(raw)]
    assert keys == sorted(keys)
    assert all((keys[i] == keys[i + 1]) == (numbers[i] == numbers[i + 1]) for i in range(len(keys) - 1))


# ---- media ------------------------------------------------------------------------------------------------------


def test_media_round_trip(spark, awkward, nothing, tmp_path):
    folder = f"file://{tmp_path}/media"
    rows = media.media_columns(awkward.repartition(3), folder).collect()
    assert len(rows) == awkward.count()
    texts = defaultdict(set)
    for r in awkward.collect():
        texts[r.doc_id].add(r.text or "")
    import tarfile

    for r in rows:
        (text,) = texts[r.doc_id]
        n, payload = media.payload_of(text)
        with open(f"{tmp_path}/media/{r.shard}", "rb") as f:
            f.seek(r.offset)
            stored = f.read(r.length)
        assert media.decode(stored) == payload and len(payload) % 576 == 0 and len(payload) >= 576
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(text.encode()), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]))
        assert (r.media_bytes, r.media_sha256) == (len(stored), hashlib.sha256(stored).hexdigest()) and (r.width, r.height) == (576, len(payload) // 576)
        with tarfile.open(f"{tmp_path}/media/{r.shard}") as tar:
            assert f"{r.digest}.png" in tar.getnames()
    assert len({(r.shard, r.offset) for r in rows}) == len({r.digest for r in rows})
    assert media.media_columns(nothing).count() == 0


# ---- classifiers ------------------------------------------------------------------------------------------------


def test_language(spark, tiny, awkward, nothing):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    learned = langid.learn_dictionaries(docs.where(common.remainder(F.col("doc_id"), 4) != 2))
    out = langid.identify(docs, learned).join(docs, "doc_id").where(common.remainder(F.col("doc_id"), 4) == 2)
    assert out.select(F.avg((F.col("lang") == F.col("lang_pred")).cast("int"))).first()[0] > 0.97
    got = {r.doc_id: r for r in langid.identify(awkward, learned).collect()}
    assert [got[i].lang_pred for i in (1, 2, 8)] == ["und"] * 3 and got[9].lang_pred != "und"
    assert all(0 <= r.score <= 1 for r in got.values())
    assert langid.identify(nothing, learned).count() == 0 and langid.learn_dictionaries(nothing) == []
    assert langid.identify(awkward, []).where("lang_pred <> 'und'").count() == 0


def held_out(spark, scored, labels, fold, label, cut):
    """(true and false positives, false and true negatives) of the held-out rows."""
    rows = scored.join(labels.where(fold == 0), "doc_id").select(label, (F.col("score") >= cut).cast("int").alias("p")).collect()
    n = Counter((r[label], r.p) for r in rows)
    return n[1, 1], n[0, 1], n[1, 0], n[0, 0]


@pytest.mark.parametrize("operator, label", [(quality, "quality"), (toxicity, "toxic")])
def test_classifiers(spark, awkward, nothing, operator, label):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    fold = common.remainder(F.col("doc_id"), 5)
    docs = docs.join(labels.select("doc_id"), "doc_id", "left_semi")
    sample = quality.learning_sample(docs, labels.where(fold != 0), label, per_class=1000, unlabelled=500, may_learn=fold != 0)
    model = operator.fit(*sample) if operator is toxicity else operator.fit(*sample[:2])
    tp, fp, fn, tn = held_out(spark, quality.score_documents(docs.where(fold == 0), model), labels, fold, label, 0.3 if label == "quality" else 0.5)
    if label == "toxic":
        assert tp >= 0.9 * (tp + fn) and tp >= 0.95 * (tp + fp)
    else:
        assert tp >= 0.99 * (tp + fn) and tn >= 0.9 * (tn + fp)
    got = quality.score_documents(awkward, model).collect()
    assert len(got) == awkward.count() and all(0 <= r.score <= 1 for r in got)
    assert quality.score_documents(nothing, model).count() == 0
    none = operator.fit([], {})
    assert all(0 <= s <= 1 for s in none.score([None, "", "x"]))
    empty_labels = labels.where("1 = 0")
    assert quality.labelled_sample(docs, empty_labels, label, per_class=5) == ([], {})
    assert operator.fit([("a b", 1)], {1: 1}).score(["a b", None]).min() >= 0


def test_learning_sample_is_bounded_and_defined(spark):
    docs = spark.createDataFrame([(i, f"{i} " * (200 if i % 2 else 1)) for i in range(50)] + [(3, "other"), (None, "no id")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(40)] + [(4, 1), (4, 0), (6, None), (None, 1), (777, 1)], "doc_id long, quality int")
    sample, counts, free = quality.learning_sample(docs, labels, "quality", per_class=10, unlabelled=5, sample_bytes=1000)
    assert counts == {0: 19, 1: 21}  # id 4 has both labels, and null says nothing
    assert sum(y == 0 for _, y in sample) == 10 and sum(len(t) for t, y in sample if y) <= 1000 and any(y for _, y in sample)
    assert 1 <= len(free) <= 5 and all(int(t.split()[0]) >= 40 for t in free)
    one, _ = quality.labelled_sample(docs, labels.where("doc_id = 1"), "quality", per_class=5, sample_bytes=1)
    assert one == [("1 " * 200, 1)]


def test_label_model_finds_planted_voters():
    rng = np.random.default_rng(4)
    n, prior = 20_000, 0.2
    y = (rng.random(n) < prior).astype(int)
    hit, miss = np.array([0.8, 0.7, 0.6, 0.5]), np.array([0.05, 0.1, 0.02, 0.1])
    votes = (rng.random((n, 4)) < np.where(y[:, None] == 1, hit, miss)).astype(float)
    copy = np.where(rng.random(n) < 0.95, votes[:, 0], rng.random(n) < 0.3)  # a voter that repeats the first
    noise = (rng.random(n) < 0.3).astype(float)
    votes = np.column_stack([votes, copy, noise])
    model = toxicity.label_model(votes, prior, oriented=5)
    assert {model.parent[4], model.parent[0]} & {0, 4} and (model.parent[0] == 4 or model.parent[4] == 0)
    # accuracies: the share of speakers in each class under the model
    post = model.posterior(votes)
    assert (votes * post[:, None]).sum(0)[:4] / post.sum() == pytest.approx(hit, abs=0.05)
    assert (votes * (1 - post)[:, None]).sum(0)[:4] / (1 - post).sum() == pytest.approx(miss, abs=0.03)
    assert ((post >= 0.5) == (y == 1)).mean() > 0.93
    # brute force: the joint probability of class and votes, voter by voter
    for v in votes[:50].astype(int):
        p = [1 - prior, prior]
        for c in (0, 1):
            for j, x in enumerate(v):
                speaks = model.speaks[j, c, v[model.parent[j]] if model.parent[j] != j else 0]
                p[c] *= speaks if x else 1 - speaks
        assert model.posterior(v[None, :])[0] == pytest.approx(p[1] / sum(p), abs=1e-9)


def test_latent_axes_equal_the_dense_decomposition():
    rng = np.random.default_rng(1)
    for shape in ((60, 200), (200, 60)):
        m = rng.standard_normal(shape) @ np.diag(0.9 ** np.arange(shape[1])) + 0.01 * rng.standard_normal(shape)
        _, _, vt = np.linalg.svd(m, full_matrices=False)
        got = quality.latent_axes([(np.arange(shape[1]), row) for row in m], shape[1], 8)
        assert np.abs(got @ got.T - vt[:8].T @ vt[:8]).max() < 1e-6


def test_latent_vectors_are_projections(spark):
    rng = random.Random(3)
    texts = [" ".join(rng.choice(["ab", "C!", "d**", "9", "word", "other", "third"]) for _ in range(rng.randrange(1, 40))) for _ in range(60)]
    model = quality.fit([(t, i % 2) for i, t in enumerate(texts)], {0: 30, 1: 30})
    m = np.zeros((60, quality.BUCKETS))
    for i, t in enumerate(texts):
        slots, tf = quality.sparse(t)
        m[i, slots] = tf
    m *= np.log(61 / (1 + (m > 0).sum(0))) + 1
    m /= np.linalg.norm(m, axis=1, keepdims=True)
    _, _, vt = np.linalg.svd(m, full_matrices=False)
    dense = m @ vt[: quality.RANK].T
    dense /= np.linalg.norm(dense, axis=1, keepdims=True)
    assert np.abs(model.vectors @ model.vectors.T - dense @ dense.T).max() < 1e-6


def test_keep_good(spark, awkward, nothing):
    model = quality.fit([("good words here", 1)] * 5 + [("### $$$ %%%", 0)] * 5, {0: 5, 1: 5})
    want = Counter((r.doc_id, r.text) for r in awkward.collect() if model.score([r.text])[0] >= 0.3)
    kept = quality.keep_good(awkward, model)
    assert Counter((r.doc_id, r.text) for r in kept.collect()) == want and kept.columns == awkward.columns
    assert quality.keep_good(nothing, model).count() == 0


def test_exact_neighbours():
    rng = random.Random(0)
    sample = [(" ".join(rng.choice(["ab", "C!", "d**", "9"]) for _ in range(30)), i % 2) for i in range(80)]
    model = quality.fit(sample, {0: 40, 1: 40})
    texts = ["ab C! d**", "9 9 9 ab", ""]
    got = model.score(texts)
    for i, v in enumerate(model.embed(texts)):
        cos = np.round(model.vectors @ v, 9)
        near = np.argsort(-cos, kind="stable")[: quality.NEIGHBOURS]
        w = np.maximum(cos[near], 0) ** 2 * model.weights[near]
        want = (w * model.labels[near]).sum() / w.sum() if w.sum() else model.prior
        assert got[i] == pytest.approx(want, abs=1e-6)


def test_language_of_long_and_short_texts_only(spark):
    long = "1 " * 15_000 + "zwo drei vier " * 3_000
    docs = spark.createDataFrame([(1, long, "de"), (2, "a", "xx"), (3, "one two three", "en"), (4, "é" * 20_000, "fr")], "doc_id long, text string, lang string")
    found = dict(langid.learn_dictionaries(docs))
    assert set(found) == {"de", "en", "fr", "xx"} and found["de"].startswith(b"zwo drei") and all(8 <= len(v) <= langid.DICT_BYTES for v in found.values())
    assert {r.doc_id: r.lang_pred for r in langid.identify(docs, sorted(found.items())).collect()}[1] == "de"


def test_language_against_brute_force(spark, tiny):
    import zstandard

    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    learned = langid.learn_dictionaries(docs)
    got = {(r.doc_id): r for r in langid.identify(docs, learned).collect()}
    how = zstandard.ZstdCompressionParameters.from_level(3, strategy=zstandard.STRATEGY_LAZY, min_match=langid.SHORTEST_MATCH, search_log=3, write_content_size=0, write_checksum=0, write_dict_id=0)
    for r in docs.limit(60).collect():
        data = r.text.lower().encode()
        sizes = {}
        for name, content in learned:
            total = 0
            for i in range(0, len(data), langid.BLOCK):
                coder = zstandard.ZstdCompressor(dict_data=zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT), compression_params=how)
                total += len(coder.compress(data[i : i + langid.BLOCK]))
            sizes[name] = total
        best = min(sizes.values())
        assert sizes[got[r.doc_id].lang_pred] == best
        second = sorted(sizes.values())[1]
        assert got[r.doc_id].rejected == (second - best < langid.NARROW * best)


def test_operators_leave_the_settings_alone(spark, awkward):
    before = {k: spark.conf.get(k, None) for k in ("spark.sql.execution.arrow.maxRecordsPerBatch", "spark.sql.shuffle.partitions", "spark.sql.adaptive.enabled")}
    simhash.near_duplicates(awkward).count()
    resemblance.keep_one(awkward).count()
    media.media_columns(awkward).count()
    substrings.remove_repeats(awkward).count()
    langid.identify(awkward, []).count()
    assert before == {k: spark.conf.get(k, None) for k in before}


def test_parity_sketches_bound_the_difference(spark):
    rng = np.random.default_rng(8)
    rows = []
    for n in (0, 1, 5, 31, 32, 33, 200, 255, 256, 257, 3000):
        a = np.unique(rng.integers(-(1 << 63), 1 << 63, n, np.int64))
        b = np.unique(np.concatenate([a[: int(len(a) * 0.9)], rng.integers(-(1 << 63), 1 << 63, n // 7, np.int64)]))
        rows.append((resemblance.parity_sketch(a).tolist(), resemblance.parity_sketch(b).tolist(), len(np.setxor1d(a, b))))
    df = spark.createDataFrame(rows, "a array<long>, b array<long>, d int")
    to = F.least(F.size("a"), F.size("b"))
    differ = F.aggregate(F.zip_with(resemblance.folded(F.col("a"), to), resemblance.folded(F.col("b"), to), lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda x, y: x + y)
    got = df.select("d", differ.alias("bits"), F.size(resemblance.folded(F.col("a"), to)).alias("n"), to.alias("to")).collect()
    assert all(r.bits <= r.d and r.n == r.to and (r.d - r.bits) % 2 == 0 for r in got) and sum(r.bits for r in got) > 0.5 * sum(r.d for r in got)
