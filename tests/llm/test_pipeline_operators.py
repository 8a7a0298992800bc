"""Decontamination, mixing, sharding and the whole pipeline against brute force."""

import random
import re
import zlib
from collections import Counter

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from supplyrisk.llm import decontaminate, mixing, sharding, toxicity
from supplyrisk.llm.common import bucket_of, key_bounds, range_of
from tests.llm.test_text_operators import slow_groups


# --- shared -------------------------------------------------------------------------------


def test_bucket_of_is_a_count_of_bounds(spark):
    for bounds in ([], [5], [1, 4, 9], list(range(0, 70, 3))):
        got = spark.range(-3, 80).select("id", bucket_of(F.col("id"), bounds).alias("b")).collect()
        assert all(r.b == sum(x <= r.id for x in bounds) for r in got)
    assert key_bounds(spark.range(0).withColumnRenamed("id", "k"), "k", 4) == []


# --- decontamination ----------------------------------------------------------------------


def words(text):
    return [w for w in re.split(r"[^\w]+|_", (text or "").lower()) if w]


def slow_overlap(doc, item):
    """Score, equal words, span and shift of the best diagonal that some mask hits."""
    d, b = words(doc), words(item)
    best = None
    n = len(b)
    if n < decontaminate.MIN_WORDS:
        return None
    if n < decontaminate.SPAN:
        at = next((i for i in range(len(d) - n + 1) if d[i : i + n] == b), None)
        return None if at is None else (n, n, 0, n, at)
    least = min(decontaminate.MIN_SCORE, -(-n * decontaminate.LEAST_SHARE // 5))
    for shift in range(-len(b), len(d)):
        same = {q: d[q + shift] == b[q] for q in range(max(0, -shift), min(len(b), len(d) - shift))}
        if not any(all(same.get(at + p) and at in same and at + decontaminate.SPAN - 1 in same for p in m) for m in decontaminate.MASKS for at in same):
            continue
        score, first, eq, top = 0, None, 0, (0, None, None, None)
        for q, ok in sorted(same.items()):
            if score <= 0:
                score, first, eq = 0, q, 0
            score += 1 if ok else -decontaminate.PENALTY
            eq += ok
            if score > top[0]:
                top = (score, eq, first, q + 1)
        if top[0] >= least and (best is None or top[0] > best[0]):
            best = (*top, top[2] + shift)
    return best


def test_overlaps_match_brute_force_with_substitutions(spark):
    rng = random.Random(12)
    vocabulary = [f"v{k}" for k in range(60)]
    items = [[rng.choice(vocabulary) for _ in range(n)] for n in (3, 5, 6, 8, 9, 9, 11, 13, 15, 18, 25, 39)]
    docs = []
    for i in range(300):
        body = [rng.choice(vocabulary) for _ in range(rng.randrange(0, 60))]
        if rng.random() < 0.7:
            part = list(rng.choice(items))
            part = part[rng.randrange(3) :]
            for _ in range(rng.randrange(0, 4)):
                part[rng.randrange(len(part))] = "sub"
            at = rng.randrange(len(body) + 1)
            body[at:at] = part
        if rng.random() < 0.1:
            body = ["x"] * rng.randrange(3) + rng.choice(items[1:6])
        docs.append((i, " ".join(w.upper() if rng.random() < 0.2 else w + rng.choice(["", ",", "!!"]) for w in body)))
    docs += [(1000, None), (1001, ""), (None, "v1 " * 40), (None, " ".join(items[-1])), (0, docs[0][1]), (1003, " ".join(items[6] + items[6]))]
    bench = [(k, " ".join(x)) for k, x in enumerate(items)] + [(50, None), (51, "")]
    df = spark.createDataFrame(docs, "doc_id long, text string").selectExpr("*", "1 AS seed", "2 AS words", "3 AS item_id")
    got = {(r.doc_id, r.item_id): (r.score, r.same, r.item_first, r.item_past, r.doc_first) for r in decontaminate.find_overlaps(df, spark.createDataFrame(bench, "item_id long, text string")).collect()}
    want = {(i, k): o for i, t in docs for k, b in bench if (o := slow_overlap(t, b))}
    assert got == want and 80 < len(want) < 250 and {k for _, k in want} == set(range(1, 12))
    kept = decontaminate.drop_contaminated(df, spark.createDataFrame(bench, "item_id long, text string"))
    assert Counter(tuple(r)[:2] for r in kept.collect()) == Counter((i, t) for i, t in docs if not any(slow_overlap(t, b) for _, b in bench)) and kept.columns == df.columns


def test_shuffled_benchmark_side_gives_the_same(spark, monkeypatch):
    text = " ".join(f"w{k}" for k in range(30))
    long = " ".join(f"n{k % 9000}" for k in range(20_000))
    rows = [(1, "x " + text), (2, "y"), (4, long + " " + text + " " + long), (5, "z " * 600_000 + text)]
    df, bench = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame([(3, text), (6, long)], "item_id long, text string")
    a = {tuple(r) for r in decontaminate.find_overlaps(df, bench).collect()}
    monkeypatch.setattr(decontaminate, "BROADCAST_SEEDS", 0)
    assert {tuple(r) for r in decontaminate.find_overlaps(df, bench).collect()} == a
    assert {r[:3] + r[6:7] for r in a} == {(1, 3, 30, 1), (4, 3, 30, 20_000), (4, 6, 20_000, 0), (5, 3, 30, 600_000)}
    assert [r.doc_id for r in decontaminate.drop_contaminated(df, bench).collect()] == [2]
    assert decontaminate.find_overlaps(df, bench.limit(0)).count() == 0


# --- mixing -------------------------------------------------------------------------------


@pytest.mark.parametrize("seed", range(6))
def test_pfair_is_within_one_block(seed):
    rng = random.Random(seed)
    weights = {f"s{k}": rng.random() ** 3 + 0.01 for k in range(rng.randrange(1, 30))}
    shares = mixing.whole_weights(weights, 256)
    assert sum(shares.values()) == 256 and min(shares.values()) >= 1
    plan = mixing.pfair_period(shares)
    assert Counter(plan) == shares
    got = Counter()
    for slot, name in enumerate(plan, 1):
        got[name] += 1
        assert all(abs(got[x] - slot * w / 256) < 1 for x, w in shares.items())


def test_mix_keeps_all_rows_and_orders_blocks(spark):
    rng = random.Random(4)
    rows = [(i, rng.choices(["a", "b", "c", None], (6, 3, 1, 1))[0]) for i in range(700)] + [(None, "a"), (5000, "solo"), (5000, "solo")]
    df = spark.createDataFrame(rows, "doc_id long, source string").selectExpr("*", "'z' AS name", "1 AS slot")
    got = mixing.mix_sources(df, block_docs=4, period=32).collect()
    assert Counter((r.doc_id, r.source) for r in got) == Counter(rows)
    by_block = {}
    for r in got:
        by_block.setdefault((r.source, r.block), []).append(r)
    assert len({rs[0].slot for rs in by_block.values()}) == len(by_block)
    for rs in by_block.values():
        assert len({r.slot for r in rs}) == 1 and sorted(r.within for r in rs) == list(range(len(rs))) and len(rs) <= 4
    for source in ("a", "b", None):
        ids = [r.doc_id for r in sorted((r for r in got if r.source == source), key=lambda r: (r.slot, r.within))]
        assert ids == sorted(ids, key=lambda i: (i is not None, i or 0))
    # First phase: shares hold at every slot while no source has run out.
    first = [r for r in got if r.phase == 0]
    order = [s for s, _ in sorted({(r.source, r.slot) for r in first}, key=lambda x: x[1])]
    sizes = Counter("?" if s is None else "=" + s for _, s in rows)
    shares = mixing.whole_weights({k: n**mixing.TEMPERATURE for k, n in sizes.items()}, 32)
    seen = Counter()
    if len(order) >= 32:
        for slot, s in enumerate(order[:32], 1):
            seen["?" if s is None else "=" + s] += 1
            assert all(abs(seen[x] - slot * w / 32) < 1 for x, w in shares.items())
    assert mixing.mix_sources(df.limit(0)).count() == 0


def test_every_slot_of_every_phase_is_within_one_block():
    rng = random.Random(9)
    blocks = {f"s{k}": rng.randrange(1, 400) for k in range(25)}
    weights = {x: rng.random() ** 4 + 0.001 for x in blocks}
    plan = mixing.plan_blocks(blocks, weights)
    assert [slot for *_, slot in plan] == list(range(sum(blocks.values())))
    done = Counter()
    for phase in range(max(p for _, _, p, _ in plan) + 1):
        total = sum(w for x, w in weights.items() if done[x] < blocks[x])
        live = {x: w / total for x, w in weights.items() if done[x] < blocks[x]}
        seen = Counter()
        for slot, (x, block, _, _) in enumerate([p for p in plan if p[2] == phase], 1):
            assert block == done[x]
            done[x] += 1
            seen[x] += 1
            assert all(abs(seen[y] - slot * w) < 1 + 1e-9 for y, w in live.items())
    assert done == blocks
    with pytest.raises(ValueError):
        mixing.plan_blocks({"a": 1}, {"a": 0.0})


def test_ten_thousand_sources():
    blocks = {f"s{k}": 1 + k % 3 for k in range(10_000)}
    plan = mixing.plan_blocks(blocks, {x: float(n) for x, n in blocks.items()})
    assert Counter(x for x, *_ in plan) == blocks and sorted(slot for *_, slot in plan) == list(range(len(plan)))


def test_mix_of_null_ids_repeats_and_large_tables(spark):
    rows = [(None if i % 3 == 0 else 7 if i % 3 == 1 else i, "ab"[i % 2], f"text {i // 4}") for i in range(3000)]
    df = spark.createDataFrame(rows, "doc_id long, source string, text string").withColumn("more", F.create_map(F.lit("k"), F.lit(1))).selectExpr("*", "1 AS tie", "2 AS k", "3 AS range")
    got = mixing.mix_sources(df, max_blocks=20).collect()
    assert Counter((r.doc_id, r.source) for r in got) == Counter(r[:2] for r in rows)
    by_slot = Counter(r.slot for r in got)
    assert len(by_slot) == 20 and set(by_slot.values()) == {150}
    assert len({(r.slot, r.within) for r in got}) == 3000
    order = mixing.mixed_order(df, block_docs=10)
    assert order.columns == df.columns
    mixed = [r.source for r in order.select("source").collect()]
    assert Counter(mixed) == Counter(r[1] for r in rows)
    spread = spark.createDataFrame([(None, f"{i}") for i in range(4000)], "doc_id long, text string").withColumn("k", F.lit(5).cast("long")).withColumn("u", F.pmod(F.xxhash64("text"), F.lit(1000)) / 1000)
    per_range = Counter(r.n for r in spread.select(range_of(spread, "k", 16, F.col("u")).alias("n")).collect())
    assert len(per_range) >= 14 and max(per_range.values()) < 500


def test_given_weights(spark):
    df = spark.createDataFrame([(i, "a" if i % 2 else "b") for i in range(400)], "doc_id long, source string")
    got = mixing.mix_sources(df, {"a": 3, "b": 1}, block_docs=1, period=8).where("phase = 0").collect()
    order = [r.source for r in sorted(got, key=lambda r: r.slot)]
    assert order[:8].count("a") == 6 and order[:80].count("a") == 60


# --- sharding -----------------------------------------------------------------------------


def slow_shards(rows, n):
    sized = sorted(((-(2**63) if i is None else i, zlib.crc32((t or "").encode()), len((t or "").encode()) + 1, i) for i, t in rows), key=lambda x: x[:3])
    total, start, out, slots = sum(x[2] for x in sized), 0, [], Counter()
    for _, crc, size, i in sized:
        s = min(n - 1, int((start + size / 2) * n / total))
        out.append((i, size, crc, s, slots[s]))
        slots[s] += 1
        start += size
    return out


def test_shards_match_brute_force(spark):
    rng = random.Random(3)
    rows = [(rng.randrange(400), "é" * rng.randrange(0, 300)) for _ in range(300)] + [(None, None), (7, "x" * 3000), (7, ""), (7, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 AS size", "2 AS shard").repartition(6)
    got = sorted((tuple(r) for r in sharding.shard_documents(df, 16).select("doc_id", "size", "text_crc32", "shard", "slot").collect()), key=repr)
    assert got == sorted(slow_shards(rows, 16), key=repr)
    sizes = Counter()
    for _, size, _, s, _ in got:
        sizes[s] += size
    assert max(sizes.values()) - min(sizes.values()) <= 2 * max(r[1] for r in got)
    assert sharding.shard_documents(df.limit(0)).count() == 0


def test_shards_of_one_frequent_id(spark):
    rng = random.Random(8)
    rows = [(rng.choice([None, 5, 5, i]), "x" * rng.randrange(0, 50)) for i in range(2000)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    got = sorted((tuple(r) for r in sharding.shard_documents(df, 16).select("doc_id", "size", "text_crc32", "shard", "slot").collect()), key=repr)
    assert got == sorted(slow_shards(rows, 16), key=repr)
    huge = spark.createDataFrame([(1, "y" * 3_000_000), (2, "z"), (3, None)], "doc_id long, text string")
    assert sorted((r.doc_id, r.size) for r in sharding.shard_documents(huge, 16).collect()) == [(1, 3_000_001), (2, 2), (3, 1)]


def test_stored_order(spark, tmp_path):
    df = spark.range(100).selectExpr("id AS doc_id", "'t' AS text").sort(F.desc("doc_id"))
    assert sharding.stored_order(df) is None
    df.write.parquet(str(tmp_path / "x"))
    back = spark.read.parquet(str(tmp_path / "x"))
    got = sharding.shard_documents(back, 4, order=sharding.stored_order(back)).orderBy("shard", "slot").collect()
    assert [r.doc_id for r in got] == list(range(99, -1, -1))


# --- pipeline -----------------------------------------------------------------------------


@pytest.fixture(scope="module")
def small(spark, tmp_path_factory):
    """A folder of tables with leaks, copies, toxic texts and odd rows."""
    base, out = "/root/testdata/sf0.001", tmp_path_factory.mktemp("sf")
    docs = spark.read.parquet(f"{base}/documents.parquet")
    item = spark.read.parquet(f"{base}/benchmark.parquet").first().text
    odd = [(9000, "Before. " + item + " After.", "en", "src1", 1), (9001, "you idiot clown and moron", "en", "src1", 1), (9002, None, None, None, None), (9003, "a b c d e f", "en", "src2", 1), (9004, "a b c d e f", "en", "src2", 1), (None, "no id here at all", "en", "src2", 1)]
    docs.union(spark.createDataFrame(odd, docs.schema)).withColumn("extra", F.lit(1)).write.parquet(f"{out}/documents.parquet")
    for t in ("labels", "benchmark"):
        spark.read.parquet(f"{base}/{t}.parquet").write.parquet(f"{out}/{t}.parquet")
    return str(out)


def test_pipeline_matches_brute_force(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    rows = {r.doc_id: r for r in docs.collect()}
    model = toxicity.fit(docs, spark.read.parquet(f"{small}/labels.parquet"))
    clean = {i: r for i, r in rows.items() if model.score(r.text) < 0.5}
    groups = slow_groups({i: r.text for i, r in clean.items() if i is not None})
    single = {i: r for i, r in clean.items() if i is None or groups[i] == i}
    items = [r.text for r in spark.read.parquet(f"{small}/benchmark.parquet").collect()]
    left = {i for i, r in single.items() if i is None or not any(slow_overlap(r.text, b) for b in items)}
    got = corpus_pipeline.run(spark, small).orderBy("shard", "slot").collect()
    assert Counter(r.doc_id for r in got) == Counter(left)
    assert 9000 not in left and 9001 not in left and 9002 in left and (9003 in left) and 9004 not in left and None in left
    order = {r.doc_id: (r.slot, r.within) for r in mixing.mix_sources(docs.where(F.col("doc_id").isNull() | F.col("doc_id").isin([i for i in left if i is not None]))).collect()}
    assert [r.doc_id for r in got] == sorted(left, key=lambda i: order[i])
    per_shard = Counter(r.shard for r in got)
    assert all(sorted(r.slot for r in got if r.shard == s) == list(range(n)) for s, n in per_shard.items())


def test_stages_keep_the_columns(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert tuple(stage(spark, docs, small).columns) == corpus_pipeline.COLUMNS
        assert stage(spark, docs.limit(0), small).count() == 0
    assert corpus_pipeline.shard(spark, docs.limit(0), small).count() == 0
