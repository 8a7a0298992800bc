"""Line chunks and exact substrings against brute force."""

import hashlib
import random

import numpy as np
import pytest

from supplyrisk.llm import line_dedup, substring_dedup


def _hash(line):
    return int(hashlib.md5(line.encode()).hexdigest()[:7], 16)


def chunks_of(text):
    """By walking: a mark two lines at least after the last mark that counted, the start being
    one; then further ends after every MAX_LINES lines."""
    lines = text.split("\n")
    hs = [_hash(x) for x in lines]
    marks, last = [0], 0
    for i, h in enumerate(hs):
        if (h + (hs[i - 1] if i else 0) * line_dedup.ROLL) % line_dedup.MIXER % line_dedup.CHUNK_LINES == 0 and i + 1 - last >= 2:
            last = i + 1
            marks.append(last)
    ends = set()
    for a, b in zip(marks, [*marks[1:], len(lines)], strict=True):
        ends |= {e for e in range(a, b - line_dedup.MIN_LINES + 1, line_dedup.MAX_LINES) if e > 0} | ({a} - {0})
    cuts = sorted(ends | {len(lines)})
    return lines, list(zip([0, *cuts[:-1]], cuts, strict=True))


def brute_lines(rows):
    firsts = {}
    for i, text in sorted(rows, key=lambda r: (-(2**63) if r[0] is None else r[0])):
        lines, chunks = chunks_of(text or "")
        for a, b in chunks:
            if b - a >= line_dedup.MIN_LINES and "\n".join(lines[a:b]).strip(" ") != "":
                firsts.setdefault("\n".join(lines[a:b]), (i, a))
    out = []
    for i, text in rows:
        lines, chunks = chunks_of(text or "")
        kept, gone = [], 0
        for a, b in chunks:
            body = "\n".join(lines[a:b])
            if body in firsts and firsts[body] != (i, a) and b - a >= line_dedup.MIN_LINES:
                gone += 1
            else:
                kept += lines[a:b]
        out.append((i, len(lines), gone, len(lines) - len(kept), "\n".join(kept)))
    return out


def test_line_chunks_match_brute_force(spark):
    rng = random.Random(3)
    pool = [f"line {k} {rng.random()}" for k in range(30)]
    stock = [[rng.choice(pool) for _ in range(rng.randrange(3, 12))] for _ in range(6)]
    rows = []
    for i in range(60):
        lines = []
        for _ in range(rng.randrange(1, 5)):
            lines += rng.choice(stock) if rng.random() < 0.6 else [f"own {rng.random()}" for _ in range(3)]
        rows.append((i, "\n".join(lines)))
    rows += [(None, rows[0][1]), (100, None), (101, ""), (102, "\n\n\n\n\n"), (103, "\n".join(["same"] * 100)), (104, "x\n" * 50 + "\n".join(["same"] * 40)), (7, rows[7][1]), (105, " \n \n ")]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 AS lines", "2 AS k")
    got = sorted((tuple(r) for r in line_dedup.dedup_lines(df).collect()), key=repr)
    want = sorted(brute_lines(rows), key=repr)
    assert got == want
    assert sum(r[2] for r in got) > 10
    assert line_dedup.dedup_lines(df.limit(0)).count() == 0


def test_chunks_of_equal_lines_and_of_all_texts():
    rng = random.Random(2)
    for n in (1, 2, 3, 7, 40, 300):
        for alphabet in ("a", "ab", "abcdefghij"):
            text = "\n".join(rng.choice(alphabet) for _ in range(n))
            want = [b - 1 for _, b in chunks_of(text)[1]]
            assert line_dedup.chunk_ends(text.encode().split(b"\n")).tolist() == want
            sizes = [b - a for a, b in chunks_of(text)[1]]
            assert all(x >= line_dedup.MIN_LINES for x in sizes[:-1])
    for line in "abcdefgh":  # most of a run of one line falls into equal chunks
        chunks = ["\n".join([line] * (b - a)) for a, b in chunks_of("\n".join([line] * 200))[1]]
        assert len(set(chunks)) <= 3


def test_lines_of_a_megabyte(spark):
    rng = random.Random(5)
    long = "\n".join(f"line {rng.random()}" for _ in range(60_000))
    rows = [(1, long), (2, long + "\nmore"), (3, "\n" * 1_000_000)]
    got = {r.doc_id: (r.n_lines, r.removed_lines) for r in line_dedup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[1] == (60_000, 0) and got[2][1] > 59_980 and got[3][1] > 999_900


def test_boundaries_resist_shifts():
    rng = random.Random(5)
    lines = [f"{rng.random()}" for _ in range(200)]
    a = {tuple(lines[x:y]) for x, y in chunks_of("\n".join(lines))[1]}
    moved = ["new"] + lines
    b = {tuple(moved[x:y]) for x, y in chunks_of("\n".join(moved))[1]}
    assert len(a & b) >= len(a) - 2


def brute_bytes(rows):
    first = {}
    for i, text in rows:
        raw = (text or "").encode()
        for p in range(len(raw) - 49):
            s = raw[p : p + 50]
            first[s] = min(first.get(s, i), i)
    out = {}
    for i, text in rows:
        raw = (text or "").encode()
        gone = np.zeros(len(raw), bool)
        for p in range(len(raw) - 49):
            if first[raw[p : p + 50]] < i:
                gone[p : p + 50] = True
        spans = int((np.diff(gone.astype(int), prepend=0) == 1).sum())
        out[i] = (len(raw), int(gone.sum()), spans, bytes(x for x, g in zip(raw, gone, strict=True) if not g))
    return out


@pytest.mark.parametrize("hot_runs", [100_000, 5])
@pytest.mark.parametrize("seed", [1, 2])
def test_substrings_match_brute_force(spark, seed, hot_runs):
    rng = random.Random(seed)
    alphabet = "ab é" if seed == 1 else "abcdefgh \n"
    word = lambda n: "".join(rng.choice(alphabet) for _ in range(n))
    stock = [word(rng.randrange(40, 200)) for _ in range(8)]
    rows = []
    for i in range(50):
        text = "".join(rng.choice(stock)[rng.randrange(20) :] if rng.random() < 0.5 else word(rng.randrange(5, 80)) for _ in range(4))
        if rng.random() < 0.3 and text:
            at = rng.randrange(len(text))
            text = text[:at] + "#" + text[at + 1 :]
        rows.append((i * 3 % 50, text))
    rows += [(60, "a" * 400), (61, "a" * 300), (62, None), (63, ""), (64, "x" * 49)]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "3 AS block", "'z' AS ids").repartition(5)
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, bytes(r.kept)) for r in substring_dedup.dedup_substrings(df, block_bytes=3000, hot_runs=hot_runs).collect()}
    assert got == brute_bytes(rows)


def test_substrings_null_ids_and_repeats(spark):
    text = "the quick brown fox jumps over the lazy dog and then runs far away from it"
    rows = [(None, text), (5, text), (5, text), (7, text + " x")]
    got = sorted(((r.doc_id, r.n_removed, r.n_spans) for r in substring_dedup.dedup_substrings(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=repr)
    n = len(text)
    assert got == [(5, n, 1), (5, n, 1), (7, n, 1), (None, 0, 0)]
    assert substring_dedup.dedup_substrings(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_long_text_over_segments():
    rng = random.Random(9)
    raw = np.frombuffer(bytes(rng.randrange(97, 123) for _ in range(5000)), np.uint8)
    old = substring_dedup.SEGMENT
    whole = substring_dedup.Runs(raw, np.array([2000, 3000]))
    substring_dedup.SEGMENT = 700
    try:
        cut = substring_dedup.Runs(raw, np.array([2000, 3000]))
    finally:
        substring_dedup.SEGMENT = old
    cover = lambda r: sorted({(d, s) for d, a, b in zip(r.doc, r.first, r.last, strict=True) for s in range(a, b + 1)})
    assert cover(whole) == cover(cut) and len(cover(whole)) == 2000 - 49 + 3000 - 49


def test_one_passage_in_ten_thousand_documents(spark):
    rng = random.Random(4)
    passage = "".join(rng.choice("abcdefgh ") for _ in range(120))
    rows = [(i, f"{rng.random()} before {passage} after {rng.random()}") for i in range(10_000)]
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, bytes(r.kept)) for r in substring_dedup.dedup_substrings(spark.createDataFrame(rows, "doc_id long, text string"), block_bytes=100_000).collect()}
    assert got == brute_bytes(rows)


def test_substrings_of_a_megabyte(spark):
    rng = random.Random(6)
    long = "".join(rng.choice("abcdefgh \n") for _ in range(1_200_000))
    rows = [(1, long), (2, long[:700_000] + "#" + long[700_000:]), (3, long[500_000:500_200]), (4, "a" * 1_000_000)]
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans) for r in substring_dedup.dedup_substrings(spark.createDataFrame(rows, "doc_id long, text string"), block_bytes=1 << 20).collect()}
    assert got == {1: (1_200_000, 0, 0), 2: (1_200_001, 1_200_000, 2), 3: (200, 200, 1), 4: (1_000_000, 0, 0)}


@pytest.mark.parametrize("seed", range(5))
def test_refinement_names_equal_windows(seed):
    rng = np.random.default_rng(seed)
    n, width = 400, substring_dedup._CONTEXT
    anchor, extra = rng.integers(0, 27, n), rng.integers(0, 27, n)
    at = np.arange(width)[None, :] - anchor[:, None]  # place relative to the anchor
    body = rng.integers(97, 99, 200).astype(np.uint8)
    context = body[at + 60]
    for _ in range(3):  # a few substitutions, left and right of the q-gram
        context[np.arange(n), rng.integers(0, width, n)] = rng.choice([97, 120], n, p=[0.8, 0.2])
    context[np.arange(width)[None, :] >= (extra + 50)[:, None]] = 0
    doc, gram = rng.integers(0, 50, n), np.sort(rng.integers(0, 3, n).astype(np.uint64))
    valid = (anchor[:, None] >= np.arange(27)) & (anchor[:, None] + 24 <= np.arange(27) + 50) & (np.arange(27) <= extra[:, None])
    got = substring_dedup.refine_windows(context, anchor, extra, doc, gram)
    least = {}
    key = lambda i, o: (int(gram[i]), int(anchor[i]) - o, context[i, o : o + 50].tobytes())
    for i, o in zip(*np.nonzero(valid), strict=True):
        least[key(i, o)] = min(least.get(key(i, o), 99), doc[i])
    for i, o in zip(*np.nonzero(valid), strict=True):
        same = any(context[j, o2 : o2 + 50].tobytes() == context[i, o : o + 50].tobytes() and doc[j] < doc[i] and anchor[j] - o2 == anchor[i] - o for j in range(n) for o2 in [anchor[j] - anchor[i] + o] if 0 <= o2 <= extra[j])
        assert bool(got[i] >> o & 1) == same
