import hashlib
import random

import numpy as np
import pytest
import xxhash

from treegrammar.llm import components, exact_dedup, simhash, skew

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, digest string, keep string, salt int"


def table(spark, rows):
    """Documents with extra columns whose names the operators use themselves."""
    return spark.createDataFrame([(i, t, "en", "s", len(t or ""), "x", "y", 3) for i, t in rows], SCHEMA)


def brute_exact(rows):
    groups: dict[bytes, list] = {}
    for i, t in rows:
        groups.setdefault(exact_dedup.normal_bytes(t), []).append((i, t or ""))
    out = []
    for body, own in groups.items():
        keep = min(own, key=lambda r: (-len(r[1]), r[0]))
        out += [(i, keep[0], len(own), i == keep[0], hashlib.sha256(body).hexdigest()) for i, t in own]
    return sorted(out)


ROWS = [(1, "a b"), (2, "ab"), (3, "a  b\n"), (4, None), (5, ""), (6, " \t\r\n\x0b\x0c"), (7, "é é"), (8, "éé"), (9, "x" * 50_000), (10, "x" * 50_000 + " "), (11, "single"), (12, "a\u00a0b"), (13, "a b"), (14, "a \x1cb")]


@pytest.mark.parametrize("bound", [16 << 20, 20])
def test_exact_groups(spark, monkeypatch, bound):
    monkeypatch.setattr(exact_dedup, "MAX_FILTER_BYTES", bound)
    got = sorted(tuple(r) for r in exact_dedup.exact_groups(spark, table(spark, ROWS)).select("doc_id", "keep_id", "group_size", "kept", "text_sha256").collect())
    assert got == brute_exact(ROWS)


def test_exact_groups_with_hot_groups(spark, monkeypatch):
    monkeypatch.setattr(skew, "HOT", 4)
    rng = random.Random(1)
    rows = [(i, "hot text" + " " * rng.randint(0, 3) if i % 3 == 0 else f"t{rng.randint(0, 40)}") for i in range(300)]
    got = sorted(tuple(r) for r in exact_dedup.exact_groups(spark, table(spark, rows)).select("doc_id", "keep_id", "group_size", "kept", "text_sha256").collect())
    assert got == brute_exact(rows)


def test_digest_collisions_are_told_apart_by_their_bytes(spark, monkeypatch):
    rows = [(1, "aa"), (2, "bb"), (3, "a a"), (4, "bb"), (5, "cc")]
    df = table(spark, rows).coalesce(1)
    real = hashlib.sha256

    class Weak:
        def __init__(self, data):
            self.data = data

        def digest(self):
            return real(b"same").digest() if self.data != b"cc" else real(b"cc").digest()

    # The functions run by value with a weak digest: all texts but one collide.
    import types

    weak = types.SimpleNamespace(sha256=Weak)
    for name in ("_digests", "_hits"):
        f = getattr(exact_dedup, name)
        globals_ = dict(f.__globals__) | {"hashlib": weak}
        monkeypatch.setattr(exact_dedup, name, types.FunctionType(f.__code__, globals_, name, f.__defaults__, f.__closure__))
        getattr(exact_dedup, name).__module__ = "__main__"
    got = {r["doc_id"]: (r["keep_id"], r["group_size"], r["kept"]) for r in exact_dedup.exact_groups(spark, df).collect()}
    assert got == {1: (3, 2, False), 3: (3, 2, True), 2: (2, 2, True), 4: (2, 2, False), 5: (5, 1, True)}


def test_repeated_rows_and_null_ids(spark):
    rows = [(1, "a"), (1, "a"), (1, "b"), (None, "a"), (2, "a ")]
    got = exact_dedup.exact_groups(spark, table(spark, rows)).collect()
    assert len(got) == 5 and sum(r["kept"] for r in got) == 2
    assert {r["keep_id"] for r in got if r["group_size"] == 4} == {2}
    kept = exact_dedup.keep_first(spark, table(spark, rows))
    assert kept.columns == table(spark, rows).columns


@pytest.mark.parametrize(
    "rows, stay",
    [
        ([(1, "a"), (1, "a"), (1, "b"), (None, "a"), (2, "a ")], [(1, "b"), (2, "a ")]),
        ([(None, "b"), (None, "c"), (1, "a"), (1, "a")], [(1, "a"), (None, "b"), (None, "c")]),
        ([(1, "a"), (1, "a "), (1, "é\t"), (1, "é"), (2, None), (2, ""), (3, " \x0b")], [(1, "a "), (1, "é\t"), (3, " \x0b")]),
        ([(None, "a"), (None, "a"), (None, "b")], [(None, "a"), (None, "b")]),
        ([(1, "a"), (2, "b")], [(1, "a"), (2, "b")]),
    ],
)
def test_rows_stay_by_their_own_flag(spark, rows, stay):
    got = [(r["doc_id"], r["text"]) for r in exact_dedup.keep_first(spark, table(spark, rows)).collect()]
    assert sorted(got, key=str) == sorted(stay, key=str)
    assert len(got) == sum(r["kept"] for r in exact_dedup.exact_groups(spark, table(spark, rows)).collect())


def test_empty_table(spark):
    assert exact_dedup.exact_groups(spark, table(spark, [])).count() == 0
    assert simhash.near_components(spark, table(spark, [])).count() == 0
    assert simhash.keep_one(spark, table(spark, [])).count() == 0


@pytest.mark.parametrize("bound", [16 << 20, 20])
def test_index_takes_batches(spark, monkeypatch, bound):
    """Runs, compaction and lookups, with all filters in one pass and with one prefix a pass."""
    monkeypatch.setattr(exact_dedup, "MAX_FILTER_BYTES", bound)
    digests = lambda rows: exact_dedup.digests(spark, table(spark, rows))
    index = exact_dedup.DigestIndex(spark)
    for rows in ([(5, "a"), (6, "b")], [(3, "a"), (7, "c")]):
        index.insert(digests(rows))
    probes = [(9, " a"), (9, "a"), (8, "new"), (None, "b"), (4, "c")]
    assert sorted((r["doc_id"] or 0, r["keep_id"]) for r in index.lookup(digests(probes)).collect()) == [(0, 6), (4, 7), (8, None), (9, 3), (9, 3)]
    first = {(r["keep_id"], r["n_rows"]) for r in index.compact().collect()}
    assert first == {(3, 2), (6, 1), (7, 1)}
    index.insert(digests([(1, "a")]))
    assert {(r["keep_id"], r["n_rows"]) for r in index.compact().collect()} == {(1, 3), (6, 1), (7, 1)}
    assert sorted((r["doc_id"] or 0, r["keep_id"]) for r in index.lookup(digests(probes)).collect()) == [(0, 6), (4, 7), (8, None), (9, 1), (9, 1)]
    assert exact_dedup.DigestIndex(spark).lookup(digests(probes)).where("keep_id is null").count() == 5


def test_filters_lose_no_digest_and_pass_few_others():
    own = [hashlib.sha256(str(i).encode()).digest() for i in range(5000)]
    filters: dict[int, list[bytes]] = {}
    for d in own:
        filters.setdefault(exact_dedup.prefix_of(d), []).append(d)
    filters = {p: [exact_dedup.bloom_filter(ds)] for p, ds in filters.items()}
    assert exact_dedup.passing(filters, own) == list(range(5000))
    other = [hashlib.sha256(b"x%d" % i).digest() for i in range(5000)]
    assert len(exact_dedup.passing(filters, other)) < 50


def test_joins_of_hot_keys(spark, monkeypatch):
    monkeypatch.setattr(skew, "HOT", 3)
    rows = spark.createDataFrame([(i, "h" if i % 2 else f"k{i % 7}") for i in range(100)] + [(200, "none")], "id long, key string")
    entries = rows.where("key <> 'none'").groupBy("key").count().withColumnRenamed("count", "n")
    for how, n in (("inner", 100), ("left", 101)):
        got = skew.join_entries(rows, entries, ["key"], "n", 101, how).collect()
        assert len(got) == n and {(r["key"], r["n"]) for r in got if r["key"] != "none"} == {(r["key"], r["n"]) for r in entries.collect()}


# SimHash


def slow_print(text):
    words = [w for w in "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "").replace("\t", " ").replace("\n", " ").replace("\r", " ").replace("\x0b", " ").replace("\x0c", " ").split(" ") if w]
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    hashed = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashed) > len(hashed))


@pytest.mark.parametrize("text", ["", None, " \n", "One", "one TWO", "one two three", "Ä ä é É B", "a b c d a b c d", "x " * 700, "a\u00a0b c\x1cd e", "w" * 3000 + " y z q"])
def test_fingerprint(text):
    assert simhash.fingerprint(text) == slow_print(text)


def brute_components(prints: dict[int, int], radius=3):
    ids = sorted(prints)
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            if (prints[a] ^ prints[b]).bit_count() <= radius:
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


def test_near_components(spark, monkeypatch):
    rng = random.Random(4)
    base = [" ".join(rng.choice("abcdefghij") + str(rng.randint(0, 9)) for _ in range(rng.randint(1, 60))) for _ in range(60)]
    texts = base + [" ".join("zz" if rng.random() < 0.02 else w for w in t.split(" ")) for t in base * 2] + ["", None, "  ", "Hello", "hello"]
    rows = list(enumerate(texts, 10))
    rng.shuffle(rows)
    got = {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in simhash.near_components(spark, table(spark, rows)).collect()}
    prints = {i: slow_print(t) for i, t in rows}
    roots = brute_components(prints)
    assert got == {i: (f"{prints[i]:016x}", roots[i]) for i in prints}
    kept = {r["doc_id"] for r in simhash.keep_one(spark, table(spark, rows)).collect()}
    assert kept == set(roots.values())


@pytest.mark.parametrize("cell_rows", [2048, 40])
def test_links_in_dense_balls_are_not_lost(spark, monkeypatch, cell_rows):
    """Hundreds of fingerprints around a centre, so that cells are split in chunks; components match brute force."""
    monkeypatch.setattr(simhash, "CELL_ROWS", cell_rows)
    rng = np.random.default_rng(2)
    centre = rng.integers(0, 1 << 62, 3)
    prints = {int(c) for c in centre}
    for c in centre.tolist():
        for _ in range(220):
            prints.add(c ^ sum(1 << int(b) for b in rng.choice(62, rng.integers(1, 6), replace=False)))
    prints |= set(rng.integers(0, 1 << 62, 200).tolist())
    df = spark.createDataFrame([(p,) for p in prints], "print long")
    got = {r["node"]: r["root"] for r in components.components(spark, simhash.print_links(spark, df)).collect()}
    want = brute_components({p: p for p in prints})
    assert {p: got.get(p, p) for p in prints} == want


@pytest.mark.parametrize(
    "rows, stay",
    [
        ([(1, "x y"), (1, "x y"), (2, "x y"), (None, "p q r"), (None, "p q r"), (None, "s t u")], [(1, "x y"), (None, "p q r"), (None, "s t u")]),
        ([(3, "a b c d"), (3, "e f g h"), (4, "a b c d"), (None, "e f g h")], [(3, "a b c d"), (3, "e f g h")]),
        ([(None, None), (None, ""), (7, "a")], [(None, None), (7, "a")]),
    ],
)
def test_one_row_of_each_component_stays(spark, rows, stay):
    """Null and repeated ids: rows stay by themselves, not by their id."""
    got = [(r["doc_id"], r["text"] or None) for r in simhash.keep_one(spark, table(spark, rows)).collect()]
    assert sorted(got, key=str) == sorted(stay, key=str)


def test_pairs_within_the_radius_are_dealt_together():
    """However three bits are changed, two segments have equal pivot distances."""
    rng = np.random.default_rng(8)
    a = rng.integers(0, 1 << 63, 3000, dtype=np.uint64)
    b = a.copy()
    for k in range(3):
        b ^= np.uint64(1) << rng.integers(0, 64, 3000).astype(np.uint64)
    x, y = (simhash.deal_keys(simhash.pivot_distances(v).astype(np.uint64)) for v in (a, b))
    assert (x == y).any(axis=1).all()
    assert (simhash.pivot_distances(a).sum(axis=1) == np.bitwise_count(a[:, None] ^ simhash.references())).all()
    assert (x[:-1] == x[1:]).mean() < 0.001


def test_pivot_table_discards_no_link():
    rng = np.random.default_rng(3)
    prints = rng.integers(0, 1 << 63, 400, dtype=np.uint64)
    prints[200:] = prints[:200] ^ (np.uint64(1) << rng.integers(0, 63, 200).astype(np.uint64))
    far = np.bitwise_count(prints[:, None] ^ simhash.references()).astype(np.uint8)
    i, j = np.triu_indices(400, 1)
    hit = simhash.linked(prints, far, i, j, 3)
    want = np.flatnonzero(np.bitwise_count(prints[i] ^ prints[j]) <= 3)
    assert hit.tolist() == want.tolist() and len(want) >= 200


def test_components_of_chains_and_stars(spark):
    links = [(i, i + 1) for i in range(100, 160)] + [(1, k) for k in range(2, 40)] + [(500, 501), (7, 7)]
    random.Random(1).shuffle(links)
    df = spark.createDataFrame(links, "a long, b long").repartition(6)
    got = {r["node"]: r["root"] for r in components.components(spark, df).collect()}
    assert got == {i: 100 for i in range(101, 161)} | {k: 1 for k in range(2, 40)} | {501: 500}
