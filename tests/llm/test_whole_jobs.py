"""What the reviewed cuts lost, on small inputs."""

import base64
import hashlib
import random
from collections import Counter
from itertools import combinations

import numpy as np
import pytest

from pyspark.sql import functions as F

from supplyrisk.llm import mixing, queries, secrets, simhash
from tests.llm.test_text_operators import base_spans


# --- near duplicates of the pipeline --------------------------------------------------------


def jaccard_groups(texts, least):
    """Smallest id of each group of ids by true Jaccard of five-word shingles, all pairs."""
    sets = {}
    for i, text in texts.items():
        w = text.lower().split()
        sets[i] = {" ".join(w[k : k + 5]) for k in range(max(1, len(w) - 4))}
    root = {i: i for i in texts}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(texts)
    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            if len(sets[a] & sets[b]) >= least * len(sets[a] | sets[b]) - 1e-9:
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


def test_near_groups_are_those_of_true_jaccard(spark):
    rng = random.Random(31)
    words = [f"w{k}" for k in range(3000)]
    texts = {}
    for c in range(60):
        body = [rng.choice(words) for _ in range(200)]
        texts[len(texts)] = " ".join(body)
        # one or two stretches of new words: Jaccard from about 0.7 to about 0.9
        new = rng.randrange(8, 34)
        at = rng.randrange(0, 160)
        texts[len(texts)] = " ".join([*body[:at], *(f"n{c}_{k}" for k in range(new)), *body[at + new :]])
    want = jaccard_groups(texts, 0.8)
    got = simhash.near_groups(spark.createDataFrame([*texts.items()], "doc_id long, text string")).collect()
    assert {r.doc_id: r.group_id for r in got} == want
    linked = sum(i != g for i, g in want.items())
    assert 10 < linked < 50


def test_large_group_of_near_copies_is_one_group(spark):
    body = [f"w{k}" for k in range(120)]
    rows = [(i, " ".join([*body[: i % 100], f"x{i}", *body[i % 100 + 1 :]])) for i in range(600)]
    got = simhash.near_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert {r.group_id for r in got} == {0}


# --- mixing -----------------------------------------------------------------------------------


@pytest.mark.parametrize("weights", [{"a": 0.999, "b": 0.001}, {"big": 1000.0, **{f"s{k}": 1.0 for k in range(600)}}, {f"s{k}": (k + 1) ** 0.5 for k in range(20)}])
def test_mix_is_within_one_block_of_the_targets(weights):
    total = sum(weights.values())
    plan = mixing.plan_blocks({x: 1 + int(1500 * w / total) for x, w in weights.items()}, weights)
    got = Counter()
    for slot, (x, block, _, at) in enumerate([p for p in plan if p[2] == 0], 1):
        assert at == slot - 1 and block == got[x]
        got[x] += 1
        assert all(abs(got[y] - slot * w / total) < 1 + 1e-9 for y, w in weights.items())


def test_mix_of_two_uneven_sources(spark):
    df = spark.createDataFrame([(i, "a" if i % 100 else "b") for i in range(3000)], "doc_id long, source string")
    got = mixing.mix_sources(df, {"a": 0.999, "b": 0.001}, block_docs=1).where("slot < 512").collect()
    assert Counter(r.source for r in got)["b"] <= 1


# --- secrets ----------------------------------------------------------------------------------


def test_base64_keys_after_equals_signs_in_paths_and_over_lines():
    tlv = lambda tag, body: bytes([tag, 0x82]) + len(body).to_bytes(2, "big") + body
    rng = random.Random(3)
    der = tlv(0x30, b"\x02\x01\x00" + b"".join(tlv(0x02, rng.randbytes(n)) for n in (256, 3, 256, 128, 128, 128, 128, 128)))
    ssh = b"openssh-key-v1\0" + (b"\0\0\0\x04none") * 2 + b"\0\0\0\0\0\0\0\x01" + rng.randbytes(200)
    for key in (der, ssh):
        plain = base64.b64encode(key).decode()
        wrapped = "\n".join(plain[k : k + 64] for k in range(0, len(plain), 64))
        for before, body, after in (("", plain, ""), ("PRIVATE_KEY=", plain, " x"), ("at foo/", plain, "\n"), ("key:\n", wrapped, "\nand more words"), ("k=", wrapped, "")):
            text = before + body + after
            assert [s for s in secrets.find_spans(text) if s[0] == "der"] == [("der", len(before), len(before) + len(body))]
        armoured = f"-----BEGIN PRIVATE KEY-----\n{wrapped}\n-----END PRIVATE KEY-----"
        assert [s[0] for s in secrets.find_spans(armoured)] == ["pem"]
    assert not secrets.find_spans("k=" + base64.b64encode(der[:-1]).decode())


def test_near_groups_of_a_whole_table(spark):
    """Every pair of the table at 0.8 or more is in one group, and no group is larger than they make it."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    sets = {r.doc_id: set(simhash.shingle_set(r.text).tolist()) for r in docs.collect()}
    holders = {}
    for i, s in sets.items():
        for h in s:
            holders.setdefault(h, []).append(i)
    shared = Counter(pair for ids in holders.values() if len(ids) > 1 for pair in combinations(sorted(ids), 2))
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for (a, b), n in shared.items():
        if 5 * n >= 4 * (len(sets[a]) + len(sets[b]) - n):
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    wordless = [i for i, s in sets.items() if not s]
    got = {r.doc_id: r.group_id for r in simhash.near_groups(docs).collect()}
    assert got == {i: min(wordless) if i in wordless else find(i) for i in sets}


@pytest.mark.parametrize("block_shingles", [300, 4000])
def test_large_keys_go_by_pairs_of_blocks(spark, block_shingles):
    rng = random.Random(11)
    rows = []
    for c in range(3):
        body = [f"w{c}_{k}" for k in range(60)]
        for _ in range(40):
            mine = list(body)
            for _ in range(rng.randrange(0, 4)):
                mine[rng.randrange(60)] = f"x{rng.random()}"
            rows.append((len(rows), " ".join(mine)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.group_id for r in simhash.near_groups(df, block_shingles=block_shingles).collect()}
    assert got == jaccard_groups(dict(rows), 0.8)


def test_chains_keep_all_within_the_total():
    rng = np.random.default_rng(2)
    kept = 0
    for _ in range(3000):
        n = rng.integers(0, 129)
        bits = np.zeros(256, np.uint8)
        bits[rng.choice(256, n, replace=False)] = 1
        apart = bits.reshape(simhash.WIDE_SEGMENTS, -1).sum(axis=1)[None, :]
        found = bool(simhash.chains(apart)[0])
        kept += found and n > simhash.WIDE_TOTAL
        assert found or n > simhash.WIDE_TOTAL
    assert kept < 900


def test_near_groups_of_odd_rows(spark):
    long = " ".join(f"word{k % 50_000}x{k}" for k in range(120_000))
    rows = [(1, long), (2, long + " and a little more"), (3, None), (4, ""), (5, " \n\t"), (6, "a"), (7, "A"), (8, "b"), (None, "a"), (None, "none has it"), (2, long + " and a little more"), (2, "b")]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 AS rep", "2 AS __lost", "3 AS __n", "'x' AS key", "4 AS label")
    got = Counter((r.doc_id, r.group_id) for r in simhash.near_groups(df).collect())
    assert got == Counter([(1, 1), (2, 1), (2, 1), (3, 3), (4, 3), (5, 3), (6, 6), (7, 6), (8, 1), (2, 1), (None, 6), (None, None)])
    kept = simhash.keep_representatives(df)
    assert kept.columns == df.columns
    assert sorted((r.doc_id or 0, (r.text or "")[:4]) for r in kept.collect()) == [(0, "a"), (0, "none"), (1, "word"), (3, ""), (6, "a")]
    assert simhash.keep_representatives(df.limit(0)).count() == 0
    twice = spark.createDataFrame([(1, "x y"), (1, "x y"), (2, "z")], "doc_id long, text string")
    assert sorted(r.doc_id for r in simhash.keep_representatives(twice).collect()) == [1, 2]


def _rsa(rng):
    tlv = lambda tag, body: bytes([tag, 0x82]) + len(body).to_bytes(2, "big") + body
    return tlv(0x30, b"\x02\x01\x00" + b"".join(tlv(0x02, b"\x01" + rng.randbytes(n)) for n in (256, 3, 256, 128, 128, 128, 128, 128)))


def test_upper_case_nested_and_encrypted_keys():
    rng = random.Random(12)
    key = _rsa(rng)
    kinds = lambda text: [s[0] for s in secrets.find_spans(text)]
    assert kinds("x " + key.hex().upper() + " y") == ["der"] and kinds("x " + key.hex().upper()[:-2]) == []
    b64 = lambda x: base64.b64encode(x).decode()
    once, twice = b64(b64(key).encode()), b64(b64(b64(key).encode()).encode())
    pem = f"-----BEGIN RSA PRIVATE KEY-----\n{b64(key)}\n-----END RSA PRIVATE KEY-----\n"
    for run in (once, twice, b64(pem.encode())):
        assert secrets.find_spans(f"data: {run}.") == [("der", 6, 6 + len(run))]
    assert kinds(b64(b64(key[:-1]).encode())) == [] and kinds(b64(b64(b64(b64(key).encode()).encode()).encode())) == []
    block = lambda head, body, kind="RSA PRIVATE KEY": f"-----BEGIN {kind}-----\n{head}{body}\n-----END {kind}-----"
    dek = "Proc-Type: 4,ENCRYPTED\nDEK-Info: AES-128-CBC,00112233445566778899AABBCCDDEEFF\n\n"
    assert kinds(block(dek, b64(rng.randbytes(640)))) == ["pem"]
    assert kinds(block(dek, b64(rng.randbytes(641)))) == [] == kinds(block("Proc-Type: 4,ENCRYPTED\n\n", b64(rng.randbytes(640)))) == kinds("ENCRYPTED " + block("", "A" * 8))
    oid = b"\x30\x0b\x06\x09\x2a\x86\x48\x86\xf7\x0d\x01\x05\x0d"
    sealed = oid + b"\x04\x81\x80" + rng.randbytes(128)
    whole = b"\x30\x81" + bytes([len(sealed)]) + sealed
    assert kinds(block("", b64(whole), "ENCRYPTED PRIVATE KEY")) == ["pem"] and kinds(block("", b64(whole[:-1]), "ENCRYPTED PRIVATE KEY")) == []
    two = "-----BEGIN RSA PRIVATE KEY-----\nnothing\n" + pem + " and " + pem
    assert kinds(two).count("pem") == 2  # a body on one line is a bare run as well


def test_hostile_texts_take_linear_time():
    marks = "-----BEGIN RSA PRIVATE KEY-----\n" * 40_000
    assert secrets.find_spans(marks) == [] and secrets.find_spans(marks + "-----END EC PRIVATE KEY-----\n" * 40_000) == []
    assert secrets.find_spans("M" * 1_000_000) == secrets.find_spans("/MIIE" * 200_000) == []
    assert len(secrets.find_spans("ab12" * 300_000)) == 1


def test_secret_query_against_brute_force(spark, tmp_path):
    """Every column of every row of the query, on the table and on odd rows."""
    rng = random.Random(5)
    key = base64.b64encode(_rsa(rng)).decode()
    rows = [(1, None), (2, ""), (None, "token=abcdefgh1"), (3, f"k={key}"), (3, f"k={key}"), (4, "é\U0001f600 password: 'x9x9x9x9x9' AKIA" + "A1" * 8 + " " + "0f" * 20)]
    base = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    docs = base.union(spark.createDataFrame([(None if i is None else i + 10**9, t) for i, t in rows], "doc_id long, text string"))
    docs.withColumn("spans", F.lit("x")).withColumn("kind", F.lit(1)).write.parquet(f"{tmp_path}/documents.parquet")
    got = Counter(tuple(r) for r in queries.op10_secrets(spark, str(tmp_path)).collect())
    want = Counter()
    for r in docs.collect():
        text = r.text or ""
        spans = base_spans(text)
        more = spans + [("der", 2, 2 + len(key))] * (f"k={key}" == text)
        joined = lambda x: ",".join(f"{k}:{a}:{b}" for k, a, b in x)
        n = Counter(k for k, _, _ in spans)
        want[(r.doc_id, n["assign"], n["access"], n["hex"], hashlib.sha256(joined(spans).encode()).hexdigest(), joined(sorted(more, key=lambda x: (x[1], secrets.KINDS.index(x[0])))))] += 1
    structural = [r for r in got if any(k in r[5] for k in ("pem:", "der:", "jwt:"))]
    assert Counter({r[:5]: n for r, n in got.items()}) == Counter({r[:5]: n for r, n in want.items()})
    assert {r for r in got if r not in structural} == {r for r in want if "der:" not in r[5]} and (10**9 + 3) in {r[0] for r in structural}
