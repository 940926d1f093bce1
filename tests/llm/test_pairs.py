"""N-gram Jaccard join, vector near-duplicates and components against brute force."""

import random
import re

import numpy as np
import pyarrow as pa
import pytest

from sparse_neighbors.llm import components, ngram_join, shared, vector_dedup
from sparse_neighbors.llm.textscan import hashed_words, shingle_hashes

DOCS = "doc_id long, text string, source string, n long"


def words(text):
    lower = re.sub(rb"[A-Z]", lambda m: m[0].lower(), (text or "").encode())
    return re.findall(rb"[^\x20\x09-\x0D]+", lower)


def shingles(text, k):
    w = words(text)
    return {b" ".join(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({b" ".join(w)} if w else set())


def brute(rows, k, num, den):
    """doc_id of every row -> (size, smallest doc_id reachable); rows with one id are one node."""
    sets = [(i, shingles(t, k)) for i, t in rows]
    parent = {i: i for i, _ in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, (i, x) in enumerate(sets):
        for j, y in sets[a + 1 :]:
            if x and y and den * len(x & y) >= num * len(x | y):
                a_, b_ = find(i), find(j)
                parent[max(a_, b_)] = min(a_, b_)
    return sorted((i, len(x), find(i)) for i, x in sets)


def make_texts(seed=3):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdefg") for _ in range(3))
    out = []
    for _ in range(12):
        base = [word() for _ in range(rng.choice([1, 2, 4, 12, 40, 150]))]
        for _ in range(rng.randint(1, 5)):
            own = list(base)
            for _ in range(rng.choice([0, 0, 1, 2, 6])):
                own[rng.randrange(len(own))] = word()
            out.append(" ".join(own))
    shared = " ".join(word() for _ in range(60))
    wide = [word() + word() for _ in range(900)]
    for n in (0, 15, 40, 150):
        own = list(wide)
        for _ in range(n):
            own[rng.randrange(len(own))] = word()
        out.append(" ".join(own))
    out.append(" ".join(wide[:500] + [word() + word() for _ in range(520)]))
    out += [f"{word()} {shared} {word()} {' '.join(word() for _ in range(n))}" for n in (1, 2, 3, 5, 20, 60)]
    out += ["", None, " \n\t ", "One", "ONE", "one two", "x " * 400, "x " * 400 + "y"]
    return [(i * 7 % 1009, t) for i, t in enumerate(out)]


@pytest.mark.parametrize("k,num,den", [(3, 9, 10), (5, 4, 5)])
def test_jaccard_components_equal_brute_force(spark, k, num, den):
    rows = make_texts()
    got = ngram_join.jaccard_components(spark.createDataFrame([(i, t, "s", 1) for i, t in rows], DOCS), k, num, den)
    assert sorted(tuple(r) for r in got.collect()) == brute(rows, k, num, den)


def test_jaccard_odd_rows(spark):
    text = "a b c d e f g h i j"
    rows = [(5, text), (3, text), (5, "u v w x y"), (9, "u v w x y"), (None, text), (None, None), (8, "q r s")]
    got = ngram_join.jaccard_components(spark.createDataFrame([(i, t, "s", 1) for i, t in rows], DOCS), 3, 9, 10)
    assert sorted((r[0] if r[0] is not None else -1, r[1], r[2] if r[2] is not None else -1) for r in got.collect()) == [(-1, 0, -1), (-1, 8, -1), (3, 8, 3), (5, 3, 3), (5, 8, 3), (8, 1, 8), (9, 3, 3)]
    kept = ngram_join.keep_one_of_each_group(spark.createDataFrame([(i, t, "s", 1) for i, t in rows if i != 5], DOCS), 3, 9, 10)
    assert kept.columns == ["doc_id", "text", "source", "n"] and sorted(r.doc_id or -1 for r in kept.collect()) == [-1, -1, 3, 8, 9]
    assert ngram_join.jaccard_components(spark.createDataFrame([], DOCS)).count() == 0


def test_all_texts_of_a_kept_id_stay(spark):
    rows = [(5, "a b c d e f g h i j", "s", 1), (5, "u v w x y z", "s", 1), (5, "u v w x y z", "r", 2), (7, "a b c d e f g h i j", "s", 1), (8, None, "s", 1), (8, None, "s", 1)]
    kept = ngram_join.keep_one_of_each_group(spark.createDataFrame(rows, DOCS), 3, 9, 10)
    assert sorted(map(tuple, kept.collect()), key=str) == [(5, "a b c d e f g h i j", "s", 1), (5, "u v w x y z", "r", 2), (8, None, "s", 1)]


def test_sketch_distance_bounds_the_difference():
    rng = np.random.default_rng(1)
    for _ in range(50):
        base = rng.integers(0, 1 << 60, 200).astype(np.uint64)
        a, b = np.unique(base[: rng.integers(50, 200)]), np.unique(base[rng.integers(0, 50) :])
        apart = np.bitwise_count(ngram_join.sketch(a).view(np.uint64) ^ ngram_join.sketch(b).view(np.uint64)).sum()
        assert apart <= len(np.setxor1d(a, b))


def test_wide_sketches_bound_the_difference(spark):
    from pyspark.sql import functions as F

    rng = np.random.default_rng(4)
    rows, want = [], []
    for i, (n, m) in enumerate([(600, 600), (1000, 1100), (513, 1025), (5000, 4200), (2048, 2049)]):
        base = np.unique(rng.integers(0, 1 << 63, n + m // 4).astype(np.uint64))
        a, b = base[:n], np.concatenate([base[m // 4 :][: m - m // 8], np.unique(rng.integers(0, 1 << 63, m // 8).astype(np.uint64))])
        wa, wb = (ngram_join.sketch(x, ngram_join.wide_words(len(x))) for x in (a, b))
        small = min(len(wa), len(wb))
        halves = [x if len(x) == small else x[:small] ^ x[small:] for x in (wa, wb)]
        assert all((x == ngram_join.sketch(y, small)).all() for x, y in zip(halves, (a, b), strict=True))
        want.append(int(np.bitwise_count((halves[0] ^ halves[1]).view(np.uint64)).sum()))
        assert want[-1] <= len(np.setxor1d(a, b)) and 64 * small >= min(len(a), len(b))
        rows.append((i, wa.tolist(), wb.tolist()))
    df = spark.createDataFrame(rows, "i int, a array<long>, b array<long>")
    got = df.select("i", ngram_join.wide_distance(F.col("a"), F.col("b")).alias("d")).orderBy("i").collect()
    assert [r.d for r in got] == want and ngram_join.wide_words(512) == 0


def test_keys_travel_once_in_nine_bytes_and_only_shared_ones_come_back():
    """Every key that sets of different names have comes back with each of these names, from 9 bytes a key."""
    rng = np.random.default_rng(4)
    pool = rng.integers(-(2**63), 2**63, 400)
    rows = [(int(rng.integers(-(2**63), 2**63)), rng.choice(pool, 30, replace=False)) for _ in range(20)]
    rows += [rows[0], (7, pool[:0])]  # an equal set of another task, and one without keys
    batch = pa.RecordBatch.from_pydict({"print_a": pa.array([a for a, _ in rows]), "keys": pa.array([k.tolist() for _, k in rows], pa.list_(pa.int64()))})
    blocks = list(ngram_join._key_blocks(5)([batch.slice(0, 9), batch.slice(9)]))
    total = sum(len(k) for _, k in rows)
    assert sum(len(x) for b in blocks for c in ("low", "names") for x in b.column(c).to_pylist()) == 9 * total
    got = set()
    for p in range(5):
        parts = [b.filter(pa.array([x == p for x in b.column("part").to_pylist()])) for b in blocks]
        for b in ngram_join._shared_keys(parts):
            pairs = list(zip(b.column("key").to_pylist(), b.column("name").to_pylist(), strict=True))
            assert not got & set(pairs) and len(set(pairs)) == len(pairs)
            got |= set(pairs)
    owners = {}
    for a, keys in rows:
        for key in keys.tolist():
            own = key % 2**64
            owners.setdefault((own >> 40) % 5 << 40 | own % 2**40, set()).add(a % 2**32)
    assert got == {(key, a) for key, names in owners.items() if len(names) > 1 for a in names} and len(got) > 50
    assert list(ngram_join._shared_keys([])) == []


def test_a_part_without_shared_keys_gives_nothing():
    one = pa.RecordBatch.from_pydict({"part": [0, 1], "low": [bytes(5), bytes(5)], "names": [b"aaaa", b"bbbb"]})
    assert list(ngram_join._shared_keys([one])) == []
    assert list(ngram_join._shared_in([np.arange(4)], [np.arange(4, dtype=np.uint32)])) == []


def test_sets_that_share_a_short_name_are_still_linked(spark, monkeypatch):
    """With names of one value for all sets, no key tells two of them apart; the name is then a key itself."""
    rows = make_texts()
    plain = ngram_join._prints

    def same(k, bands):
        def run(batches):
            for batch in plain(k, bands)(batches):
                a = np.asarray(batch.column("print_a"))
                yield batch.set_column(2, "print_a", pa.array(a & ~np.int64(0xFFFFFFFF)))

        return run

    monkeypatch.setattr(ngram_join, "_prints", same)
    got = ngram_join.jaccard_components(spark.createDataFrame([(i, t, "s", 1) for i, t in rows], DOCS), 3, 4, 5)
    assert sorted(map(tuple, got.collect())) == brute(rows, 3, 4, 5)


def test_linked_sets_share_a_key():
    rng = np.random.default_rng(2)
    for bands in (ngram_join.Bands(9, 10), ngram_join.Bands(4, 5)):
        for n in (10, 11, 19, 30, 95, 400, 3000):
            base = np.unique(rng.integers(0, 1 << 63, n).astype(np.uint64))
            for _ in range(20):
                change = int(rng.integers(1, max(2, n * (bands.den - bands.num) // bands.den + 1)))
                other = np.unique(np.concatenate([base[rng.permutation(len(base))[change:]], rng.integers(0, 1 << 63, int(rng.integers(0, change + 1))).astype(np.uint64)]))
                both, union = len(np.intersect1d(base, other)), len(np.union1d(base, other))
                if both < union and bands.den * both >= bands.num * union:
                    assert len(np.intersect1d(ngram_join.piece_keys(base, bands), ngram_join.piece_keys(other, bands)))


def test_long_texts_are_read_whole(monkeypatch):
    import pyarrow as pa

    from sparse_neighbors.llm import textscan

    column = pa.array(["a b " * 3000, None, "Ä x\u00a0y Z", "w" * 5000 + " end", ""])
    whole = [(i, j, b.tolist(), w.tolist()) for i, j, b, w in hashed_words(column)]
    monkeypatch.setattr(textscan, "SLICE", 1000)
    cut = [(i, j, b, w) for i, j, b, w in ((i, j, b, w) for i, j, b, w in textscan.hashed_words(column))]
    flat = np.concatenate([w for *_, w in cut])
    assert flat.tolist() == [x for *_, w in whole for x in w]
    owner, hashes = shingle_hashes(np.array([0, 2, 5]), flat[:5], 3)
    assert owner.tolist() == [1, 0] and len(set(hashes.tolist())) == 2


def test_components_equal_union_find(spark):
    rng = random.Random(4)
    edges = [(rng.randrange(60), rng.randrange(60)) for _ in range(45)] + [(100 + i, 101 + i) for i in range(20)] + [(None, 1), (7, 7)]
    parent = list(range(200))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        if a is not None:
            x, y = find(a), find(b)
            parent[max(x, y)] = min(x, y)
    got = {r.node: r.component for r in components.connected_components(spark.createDataFrame(edges, "u long, v long")).collect()}
    nodes = {x for a, b in edges if a is not None and a != b for x in (a, b)}
    assert got == {n: find(n) for n in nodes}
    assert components.connected_components(spark.createDataFrame([], "u long, v long")).count() == 0


def brute_vectors(rows, cosine):
    usable = {}
    for n, (i, v, label) in enumerate(rows):
        if i is not None and label is not None and v and all(x is not None and np.isfinite(x) for x in v) and any(v):
            x = np.array(v, float)
            usable[n] = (i, x / np.linalg.norm(x), label)
    links = {n: 0 for n in range(len(rows))}
    comp = {n: rows[n][0] for n in range(len(rows))}
    near = [(a, b) for a in usable for b in usable if a < b and usable[a][2] == usable[b][2] and len(usable[a][1]) == len(usable[b][1]) and usable[a][1] @ usable[b][1] >= cosine]
    for a, b in near:
        links[a] += 1
        links[b] += 1
    for _ in range(len(rows)):
        for a, b in near:
            comp[a] = comp[b] = min(comp[a], comp[b])
    return sorted((rows[n][0] if rows[n][0] is not None else -1, links[n], comp[n] if comp[n] is not None else -1) for n in range(len(rows)))


def test_vector_near_duplicates_equal_brute_force(spark):
    rng = np.random.default_rng(8)
    base = rng.normal(size=(30, 16))
    rows = [(int(i), (base[i % 30] + rng.normal(size=16) * rng.choice([0, 0.02, 0.2])).tolist(), int(i % 2)) for i in range(120)]
    rows += [(200, None, 0), (201, [0.0] * 16, 0), (202, [float("nan")] * 16, 0), (203, rows[0][1], None), (204, [], 0), (205, [1.0, None] * 8, 0), (None, rows[0][1], 0), (206, rows[0][1], 0), (206, rows[0][1], 0), (207, [1.0, 2.0], 0), (208, [2.0, 4.0], 0)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    got = vector_dedup.near_duplicates(df, 0.93).collect()
    assert sorted((r.vec_id if r.vec_id is not None else -1, r.n_links, r.component_id if r.component_id is not None else -1) for r in got) == brute_vectors(rows, 0.93)
    assert all(r.kept == (r.vec_id == r.component_id) for r in got if r.vec_id is not None)
    assert vector_dedup.near_duplicates(df.where("false"), 0.93).count() == 0


def test_table_distances_bound_true_distances():
    rng = np.random.default_rng(3)
    x = vector_dedup.unit(rng.normal(size=(500, 20)))
    q = vector_dedup.Quantiser.fit(x, 4)
    lists = vector_dedup.nearest(x, q.centres, 1)[:, 0]
    codes, missed = q.encode(x, lists)
    own = lists == 0
    seen = np.sqrt(q.distances(x[:50], 0, codes[own]))
    true = np.sqrt(((x[:50, None] - x[own]) ** 2).sum(2))
    assert (np.abs(seen - true) <= missed[own] + 1e-9).all()


def test_vector_recall_with_many_lists():
    """More lists than probes: links found among vectors that share a list by the two-sided probing rule, against brute force."""
    rng = np.random.default_rng(11)
    centres = vector_dedup.unit(rng.normal(size=(700, 48)))
    near = vector_dedup.unit(np.repeat(centres, 9, 0) + rng.normal(size=(6300, 48)) * 0.035)
    x = near[rng.permutation(len(near))]
    lists = -(-len(x) // vector_dedup.LIST_ROWS)
    assert lists > vector_dedup.PROBES
    q = vector_dedup.Quantiser.fit(x, lists)
    probes = vector_dedup.nearest(x, q.centres, vector_dedup.PROBES)
    own = probes[:, 0]
    found = total = 0
    for a in range(0, len(x), 700):
        i, j = np.nonzero(x[a : a + 700] @ x.T >= 0.93)
        i += a
        i, j = i[i < j], j[i < j]
        total += len(i)
        found += int(((probes[i] == own[j][:, None]).any(1) | (probes[j] == own[i][:, None]).any(1)).sum())
    assert total > 5000 and found >= 0.9 * total


def test_only_texts_of_few_pairs_go_to_python_and_in_short_batches(spark, monkeypatch):
    """Few ids are joined before Python sees a text; every job of the join has short batches, and the session's limit is back afterwards."""
    base = [f"w{i}" for i in range(40)]
    rows = [(1, " ".join(base), "s", 1), (2, " ".join([*base, "x"]), "s", 1), (3, " ".join(base[::-1]), "s", 1), (4, "", "s", 1)]
    own, seen = spark.conf.get(shared.BATCH_ROWS), set()
    monkeypatch.setattr(ngram_join, "materialize", lambda df, name, f=ngram_join.materialize: (seen.add(df.sparkSession.conf.get(shared.BATCH_ROWS)), f(df, name))[1])
    monkeypatch.setattr(ngram_join, "_id_filter", lambda *a: pytest.fail("all texts go to Python"))
    got = ngram_join.jaccard_components(spark.createDataFrame(rows, DOCS), 3, 9, 10)
    assert {(r["doc_id"], r["component_id"]) for r in got.collect()} == {(1, 1), (2, 1), (3, 3), (4, 4)}
    assert seen == {str(ngram_join.BATCH)} and spark.conf.get(shared.BATCH_ROWS) == own


def test_linked_sets_share_a_key_that_neither_leaves_out():
    """Whatever the order of keys, linked sets keep a common one when each leaves out as many of the first as it may."""
    rng = np.random.default_rng(5)
    for bands in (ngram_join.Bands(9, 10), ngram_join.Bands(4, 5), ngram_join.Bands(1, 2)):
        for n in (2, 5, 10, 19, 30, 95, 400, 1500):
            base = np.unique(rng.integers(0, 1 << 63, n).astype(np.uint64))
            for _ in range(20):
                gone, more = (int(rng.integers(0, max(2, n * (bands.den - bands.num) // bands.den + 2))) for _ in range(2))
                other = np.unique(np.concatenate([base[rng.permutation(len(base))[gone:]], rng.integers(0, 1 << 63, more).astype(np.uint64)]))
                both, union = len(np.intersect1d(base, other)), len(np.union1d(base, other))
                if both == union or not len(other) or bands.den * both < bands.num * union:
                    continue
                common = np.intersect1d(ngram_join.piece_keys(base, bands), ngram_join.piece_keys(other, bands))
                kept = []
                for s in (base, other):
                    keys, (side, *spare) = ngram_join.piece_keys(s, bands), ngram_join.spare_keys(len(s), bands)
                    for bit in (0, 1):  # the common keys first: the worst order for them
                        of_band = sorted((int(x) for x in keys if int(x) & 1 == bit), key=lambda x: (x not in common, x))
                        kept += of_band[spare[bit != side] :]
                assert len(kept) > len(set(kept))


def test_a_passage_of_unlinked_texts_brings_few_of_them_together(spark, monkeypatch):
    """Texts that share a short passage and nothing else leave out the keys that it gives them; the linked ones among them are found."""
    rng = random.Random(6)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(5))
    line = " ".join(word() for _ in range(12))
    rows = [(i, f"{line} {' '.join(word() for _ in range(180 + i % 30))}") for i in range(150)]
    rows += [(1000 + i, rows[i][1] + " " + word()) for i in range(5)]
    met = {}
    monkeypatch.setattr(ngram_join, "materialize", lambda df, name, f=shared.materialize: (out := f(df, name), met.setdefault(name, out.count()))[0])
    got = ngram_join.jaccard_components(spark.createDataFrame([(i, t, "s", 1) for i, t in rows], DOCS), 5, 4, 5)
    assert sorted(map(tuple, got.collect())) == brute(rows, 5, 4, 5)
    assert met["buckets"] < 5 * len(rows), met
