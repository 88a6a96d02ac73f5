"""SimHash, vantage-point trees, components and decontamination against brute force."""

import random

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from modelsort.llm import catalog, components, decontaminate, simhash

DOCS = "doc_id long, text string, extra string"


def plain_print(text):
    lower = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    words = [w for w in "".join(" " if c in " \t\n\x0b\x0c\r" else c for c in lower).split(" ") if w]
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def plain_components(prints, ids, radius=3):
    parent = {i: i for i in ids}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in range(len(ids)):
        for b in range(a):
            if bin(prints[a] ^ prints[b]).count("1") <= radius:
                x, y = find(ids[a]), find(ids[b])
                parent[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


def texts():
    rnd = random.Random(5)
    words = [f"w{i}" for i in range(300)]
    base = [" ".join(rnd.choice(words) for _ in range(rnd.choice([1, 2, 3, 40, 400]))) for _ in range(60)]
    near = []
    for t in base[:20]:
        w = t.split()
        w[len(w) // 2] = "changed"
        near.append(" ".join(w))
    odd = [None, "", "  \n", "A", "a", "É mixed case", "long " * 30_000, base[0], base[0], base[1].upper()]
    return base + near + odd


def test_fingerprints_and_components(spark):
    rows = [(i, t, "x") for i, t in enumerate(texts())]
    found = simhash.near_duplicates(spark.createDataFrame(rows, DOCS).repartition(5)).collect()
    prints = [plain_print(t) for _, t, _ in rows]
    assert {r["doc_id"]: r["print"] % (1 << 64) for r in found} == dict(enumerate(prints))
    assert {r["doc_id"]: r["component_id"] for r in found} == plain_components(prints, [i for i, _, _ in rows])


def test_tree_finds_every_pair_within_the_radius():
    rng = np.random.default_rng(3)
    centres = rng.integers(0, 2**63, 40, dtype=np.uint64)
    flips = [c ^ np.bitwise_or.reduce(np.uint64(1) << rng.integers(0, 64, rng.integers(1, 5), dtype=np.uint64)) for c in centres for _ in range(10)]
    prints = np.unique(np.concatenate([centres, np.array(flips, np.uint64), np.array([0, 1, 3, 7, 15, 2**64 - 1], np.uint64)]))
    q, x = simhash.VantageTree(prints).within(prints, 3)
    want = {(i, j) for i in range(len(prints)) for j in np.flatnonzero(np.bitwise_count(prints[i] ^ prints) <= 3).tolist()}
    assert set(zip(q.tolist(), x.tolist(), strict=True)) == want
    assert len(simhash.VantageTree(np.zeros(0, np.uint64)).within(prints, 3)[0]) == 0


@pytest.mark.parametrize("parts", [2, 4, 8])
def test_shards_meet_every_near_pair_once(parts):
    steps = simhash._forward_steps(parts, 3)
    assert len(steps) == len(set(steps)) and tuple([0] * parts) in steps
    assert all(tuple(-d for d in s) not in steps for s in steps if any(s))


def test_shard_levels_agree(spark, monkeypatch):
    rows = [(i, t, "x") for i, t in enumerate(texts())]
    df = spark.createDataFrame(rows, DOCS)
    small = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(df).collect()}
    monkeypatch.setattr(simhash, "SHARD_CLASSES", 0.01)
    assert {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(df).collect()} == small


def test_nulls_repeats_and_empty_tables(spark):
    rows = [(None, "same text here", "a"), (4, "same text here", "b"), (4, "same text here", "b"), (9, None, "c"), (None, None, "d")]
    found = {(r["doc_id"], r["component_id"]) for r in simhash.near_duplicates(spark.createDataFrame(rows, DOCS)).collect()}
    assert found == {(None, 4), (4, 4), (9, 9), (None, 9)}
    kept = simhash.deduplicate(spark.createDataFrame(rows, DOCS))
    assert kept.columns == ["doc_id", "text", "extra"]
    assert sorted(str(r["doc_id"]) for r in kept.collect()) == ["4", "9", "None", "None"]
    assert simhash.near_duplicates(spark.createDataFrame([], DOCS)).count() == 0


def test_documents_without_id_link_others(spark, monkeypatch):
    prints = {"a": 0, "b": 7, "c": 63, "far": 2**40 - 1}
    monkeypatch.setattr(simhash, "fingerprint", lambda text, size=3: F.element_at(F.create_map(*(x for k, v in prints.items() for x in (F.lit(k), F.lit(v).cast("long")))), text))
    df = spark.createDataFrame([(1, "a", ""), (None, "b", ""), (2, "c", ""), (None, "far", "")], DOCS)
    found = sorted((str(r["doc_id"]), str(r["component_id"])) for r in simhash.near_duplicates(df).collect())
    assert found == [("1", "1"), ("2", "1"), ("None", "1"), ("None", "None")]


def test_dedup_keeps_unlike_texts_of_one_id_and_clashing_columns(spark):
    rng = random.Random(2)
    a, b = (" ".join(f"{c}{rng.randrange(10**6)}" for _ in range(200)) for c in "ab")
    rows = [(5, a, 1, 2, 3), (5, b, 4, 5, 6), (3, a, 7, 8, 9), (8, "", 0, 0, 0), (9, None, 1, 1, 1)]
    df = spark.createDataFrame(rows, "doc_id long, text string, __keep int, `__lead` int, `a.b` int")
    kept = simhash.deduplicate(df)
    assert kept.columns == df.columns
    assert {tuple(r) for r in kept.collect()} == {rows[1], rows[2], rows[3]}


def test_near_copies_in_pieces():
    prints = np.arange(256, dtype=np.uint64)
    pieces = list(simhash.VantageTree(prints).near(prints, 8, most=100))
    assert len(pieces) > 100 and sum(len(q) for q, _ in pieces) == 256 * 256


def test_components_of_paths_and_stars(spark):
    chain = [(i, i + 1) for i in range(100, 140)]
    star = [(7, i) for i in range(8, 60)]
    df = spark.createDataFrame([*chain, *star, (3, 3), (None, 5), (1, 2), (2, 1)], "u long, v long")
    found = {r["node"]: r["component"] for r in components.connected_components(df).collect()}
    assert all(found[i] == 100 for i in range(101, 141)) and all(found[i] == 7 for i in range(8, 60)) and found[2] == 1
    assert 3 not in found and 5 not in found
    assert components.connected_components(spark.createDataFrame([], "u long, v long")).count() == 0


ITEMS = [("i1", "one two three four five six seven eight nine ten eleven twelve thirteen fourteen"), ("i2", "short item"), ("i3", "One Two three FOUR five six seven eight nine ten eleven twelve thirteen"), ("i4", ""), ("i4b", None), ("i5", "été naïve größe"), ("i2", "other words")]
TEXTS = [
    "prefix one two three four five six seven eight nine ten eleven twelve thirteen fourteen suffix",
    "one two three four five six seven eight nine ten eleven twelve",
    "a short item, then a SHORT-ITEM; other\nwords",
    "ÉTÉ été naïve größe ende",
    "short",
    "",
    None,
    "x " * 5000 + "short item",
    "one two three four five six seven eight nine ten eleven twelve thirteen " * 3,
    "item",
    "short item",
]


def test_decontamination_equals_brute_force(spark):
    docs = spark.createDataFrame([(i, t, "e") for i, t in enumerate(TEXTS)], DOCS).repartition(3)
    bench = spark.createDataFrame(ITEMS, "item_id string, text string")
    real = [(n, t) for n, t in ITEMS if t is not None]
    for passes in (4_000_000, 60):
        found = {r["doc_id"]: r["match"] for r in decontaminate.with_matches(docs, bench, pass_chars=passes).collect()}
        for i, t in enumerate(TEXTS):
            words, hits, items, digest, bad = decontaminate.brute_force(t, real)
            m = found[i]
            assert (m["n_words"], m["n_hit"], len(m["items"])) == (words, hits, items)
            assert sum(s["stop"] - s["start"] for s in m["spans"]) == hits
            assert (m["longest"]["words"] if m["longest"] else 0) == decontaminate.brute_longest(t, real)
            if m["longest"]:
                own = next(words for name, text in real if name == m["longest"]["item_id"] for words in [decontaminate.plain_words(text)] if words[m["longest"]["item_word"] :][: m["longest"]["words"]] == decontaminate.plain_words(t)[m["longest"]["doc_word"] :][: m["longest"]["words"]])
                assert own
    assert found[0]["longest"]["words"] == 14 and found[0]["longest"]["doc_word"] == 1
    kept = decontaminate.decontaminate(docs, bench)
    assert kept.columns == ["doc_id", "text", "extra"]
    clash = docs.withColumn("__match", F.lit("mine")).withColumn("__more", F.lit(1))
    assert {r["__match"] for r in decontaminate.decontaminate(clash, bench).collect()} == {"mine"}
    assert {r["doc_id"] for r in kept.collect()} == {i for i, t in enumerate(TEXTS) if not decontaminate.brute_force(t, real)[4]}


def test_decontamination_without_items_or_documents(spark):
    docs = spark.createDataFrame([(1, "a b", "e")], DOCS)
    none = spark.createDataFrame([], "item_id string, text string")
    assert decontaminate.with_matches(docs, none).first()["match"]["n_hit"] == 0
    assert decontaminate.with_matches(docs.limit(0), none).count() == 0


def test_random_windows_equal_brute_force():
    rng = random.Random(11)
    words = ["a", "b", "c"]
    items = [(f"i{k}", " ".join(rng.choice(words) for _ in range(rng.choice([2, 5, 13, 15])))) for k in range(12)]
    index = decontaminate.BenchmarkIndex.build([n for n, _ in items], [t for _, t in items])
    import pyarrow as pa

    from modelsort.llm.bytetext import utf8_view

    docs = [" ".join(rng.choice(words) for _ in range(rng.randrange(0, 60))) for _ in range(40)]
    for doc, got in zip(docs, index.match(*utf8_view(pa.array(docs))).to_pylist(), strict=True):
        assert (got["n_words"], got["n_hit"], len(got["items"])) == decontaminate.brute_force(doc, items)[:3]
        assert (got["longest"]["words"] if got["longest"] else 0) == decontaminate.brute_longest(doc, items)


def test_suffix_arrays_are_sorted():
    rng = np.random.default_rng(1)
    for most in (1, 3, 2**20, 2**33):
        ids = np.zeros(500 + decontaminate.DEPTH + 1, np.int64)
        ids[:500] = rng.integers(0, most + 1, 500)
        ids[100:160] = ids[300:360]
        array = decontaminate.suffix_array(ids, 500, most)
        keys = [tuple(ids[i : i + decontaminate.DEPTH].tolist()) for i in array]
        assert sorted(array.tolist()) == list(range(500)) and keys == sorted(keys)


def test_long_matches_and_words_of_one_hash(monkeypatch):
    import pyarrow as pa

    from modelsort.llm.bytetext import utf8_view

    item = " ".join(f"w{i}" for i in range(90))
    docs = [f"w1 w2 {item} w0", " ".join(f"w{i}" for i in range(20, 70)) + " x " + " ".join(f"w{i}" for i in range(5, 70)), "w3", "", "w88 w89 w0 w1"]
    index = decontaminate.BenchmarkIndex.build(["a"], [item])
    got = index.match(*utf8_view(pa.array(docs))).to_pylist()
    assert [g["longest"]["words"] if g["longest"] else 0 for g in got] == [90, 65, 1, 0, 2]
    assert got[1]["longest"] == {"item_id": "a", "words": 65, "doc_word": 51, "item_word": 5}
    # Training words whose hash is that of a benchmark word are told apart by their bytes.
    monkeypatch.setattr(decontaminate, "word_hashes", lambda data, starts, ends: (ends - starts).astype(np.uint64))
    index = decontaminate.BenchmarkIndex.build(["a"], ["a bb ccc"])
    got = index.match(*utf8_view(pa.array(["x yy zzz", "a bb ccc", "a bb ddd"]))).to_pylist()
    assert [g["n_hit"] for g in got] == [0, 3, 0] and [g["longest"]["words"] if g["longest"] else 0 for g in got] == [0, 3, 2]


def test_queries_have_the_contract_columns(spark):
    one = catalog.op1_simhash_near_dedup(spark, "/root/testdata/sf0.001")
    assert one.columns[:3] == ["doc_id", "fingerprint", "component_id"] and one.count() == 200
    assert all(len(r["fingerprint"]) == 16 for r in one.collect())
    two = catalog.op2_benchmark_decontamination(spark, "/root/testdata/sf0.001")
    assert dict(two.dtypes) == {"doc_id": "bigint", "n_words": "bigint", "n_hit": "bigint", "n_items": "bigint", "items_sha256": "string", "contaminated": "boolean"}


def test_every_group_keeps_a_row_when_ids_repeat(spark):
    a, b, c = ("alpha beta gamma delta " * 5, "one two three four five " * 5, "red green blue black white " * 5)
    for rows, wanted in (
        ([(3, a), (5, a), (5, b)], {(3, a), (5, b)}),  # a copy and a unique text of one id
        ([(5, a), (5, b), (5, c), (5, b)], {(5, a), (5, b), (5, c)}),  # unique texts of one id, one of them twice
        ([(5, a), (5, b), (7, a), (7, b), (9, c)], {(5, a), (5, b), (9, c)}),
    ):
        found = simhash.deduplicate(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect()
        assert {tuple(r) for r in found} == wanted and len(found) == len(wanted)
