from collections import Counter

import pytest

from tablevec.llm import sharding


def _brute(shards, slots):
    import hashlib

    orders = []
    for s in shards:
        d = hashlib.sha256(s.encode()).digest()
        o, k = int.from_bytes(d[:8], "big") % slots, int.from_bytes(d[8:16], "big") % (slots - 1) + 1
        orders.append([(o + j * k) % slots for j in range(slots)])
    table, turn = {}, 0
    while len(table) < slots:
        order = orders[turn % len(shards)]
        table[next(s for s in order if s not in table)] = turn % len(shards)
        turn += 1
    return [table[s] for s in range(slots)]


def test_table_is_that_of_plain_turns():
    names = [f"n{i}" for i in range(7)]
    assert list(sharding.lookup_table(names, 101)) == _brute(names, 101)


def test_shares_are_even_and_few_slots_move():
    names = [f"n{i}" for i in range(20)]
    old = sharding.lookup_table(names, 10007)
    counts = Counter(old.tolist())
    assert max(counts.values()) - min(counts.values()) <= 1
    new = sharding.lookup_table(names[:-1], 10007)
    moved = sum(1 for a, b in zip(old, new) if a != 19 and a != b)
    assert moved < 0.12 * 10007


def test_wrong_sizes_are_refused():
    for names, slots in (([], 7), (["a", "a"], 7), (["a"], 8), (["a", "b", "c"], 3)):
        with pytest.raises(ValueError):
            sharding.lookup_table(names, slots)


def test_rows_follow_the_table(spark):
    df = spark.createDataFrame([(1, "q"), (1, "q"), (None, "r"), (5, None)], "doc_id long, shard string")
    rows = sharding.place(df, "doc_id").collect()
    assert len(rows) == 4 and set(rows[0].asDict()) == {"doc_id", "slot", "shard"}
    owner = sharding.lookup_table(sharding.SHARDS)
    assert all(r["shard"] == sharding.SHARDS[owner[r["slot"]]] for r in rows)
    assert len({r["slot"] for r in rows if r["doc_id"] == 1}) == 1
    assert sharding.place(df.limit(0), "doc_id").count() == 0


def test_written_folders_hold_every_row(spark, tmp_path):
    df = spark.range(2000).withColumnRenamed("id", "doc_id")
    placed = sharding.place(df, "doc_id", shards=["a", "b", "c"], slots=101)
    sharding.write_shards(placed, str(tmp_path / "out"))
    back = spark.read.parquet(str(tmp_path / "out"))
    assert sorted(r["doc_id"] for r in back.collect()) == list(range(2000))
    assert set(r["shard"] for r in back.select("shard").distinct().collect()) == {"a", "b", "c"}
