import hashlib

import numpy as np
import pytest

from edgefold.llm import induced_sort, suffix_dedup as sd


def brute(rows, length=100):
    seen, out = set(), []
    for d, t in sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or "")):
        raw, gone = (t or "").encode(), set()
        for p in range(len(raw) - length + 1):
            w = raw[p : p + length]
            if w in seen:
                gone.update(range(p, p + length))
            seen.add(w)
        kept = bytes(c for i, c in enumerate(raw) if i not in gone)
        runs = sum(1 for i in gone if i - 1 not in gone)
        out.append((d, len(raw), len(gone), runs, hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=str)


def test_suffix_array_and_shared_prefixes_are_exact():
    draw = np.random.default_rng(0)
    for it in range(120):
        n, s, cap = int(draw.integers(1, 120)), int(draw.integers(1, 5)), int(draw.integers(3, 150))
        t = draw.integers(0, s, n).astype(np.uint16)
        if it % 5 == 0:
            t = np.tile(t[:7], 12)[: n + 20]
        seq = t.tolist()
        order, shared = induced_sort.suffix_array(t, cap, s + 1, induced_sort.Room(64 if it % 2 else 1 << 20))
        assert sorted(order.tolist()) == list(range(len(seq)))
        for k in range(1, len(seq)):
            a, b = seq[order[k - 1] :], seq[order[k] :]
            m = next((i for i, (x, y) in enumerate(zip(a[:cap], b[:cap], strict=False)) if x != y), min(cap, len(a), len(b)))
            assert a[:cap] <= b[:cap] and shared[k] == m


def test_queue_spills_and_keeps_order():
    room = induced_sort.Room(limit=400)
    queue = induced_sort.DiskQueue(2, room, level=3)
    for i in range(10):
        queue.put(1, np.arange(i * 10, i * 10 + 10, dtype=np.int32), np.full(10, i, dtype=np.uint8))
    assert room.spilled[3] > 0
    positions, shared = queue.take(1)
    assert positions.tolist() == list(range(100)) and shared[::10].tolist() == list(range(10)) and queue.take(0) is None


@pytest.mark.parametrize("descending", [False, True])
def test_queue_of_names_merges_its_runs(descending):
    draw = np.random.default_rng(2)
    queue = induced_sort.NameQueue(descending, induced_sort.Room(0), 1)
    want = {}
    for p in range(2000):
        s = int(draw.integers(0, 300))
        want.setdefault(s, []).append(p)
        queue.lists.setdefault(s, []).append(p)
        queue.held += 1
        if queue.held > queue.most:
            queue.spill()
    assert len(queue.runs) > 20
    for s in sorted(want, reverse=descending):
        got = []
        while piece := queue.take(s):
            got += piece
        assert got == want[s]
    assert queue.runs == [] and queue.lists == {}


def test_sort_spills_on_every_level_and_stays_exact(monkeypatch):
    """Memory for the sort is a fiftieth of what its arrays take; names need several levels."""
    monkeypatch.setattr(induced_sort, "PIECE", 700)
    draw = np.random.default_rng(8)
    words = ["".join(chr(97 + c) for c in draw.integers(0, 6, k)) for k in draw.integers(2, 9, 60)]
    phrases = [" ".join(draw.choice(words, 12)) for _ in range(30)]
    text = np.frombuffer(". ".join(draw.choice(phrases, 250)).encode(), np.uint8).astype(np.uint16)
    room = induced_sort.Room(limit=3_000)
    order, shared = induced_sort.suffix_array(text, 100, 257, room)
    plain = induced_sort.suffix_array(text, 100, 257, induced_sort.Room(1 << 30))
    assert (order == plain[0]).all() and (shared == plain[1]).all()
    raw = text.astype(np.uint8).tobytes()
    assert order.tolist() == sorted(range(len(raw)), key=lambda i: raw[i:])
    assert len(raw) * 10 > 50 * room.limit and sorted(room.spilled) == list(range(len(room.spilled))) and len(room.spilled) >= 4
    assert all(size > 1_000 for size in list(room.spilled.values())[:3])


def test_equal_windows_have_equal_anchors():
    draw = np.random.default_rng(3)
    raw = bytes(draw.integers(97, 101, 4000).tolist())
    spans = {}
    for h, starts, n in sd.anchors(raw):
        for a, s, k in zip(h.tolist(), starts.tolist(), n.tolist()):
            for p in range(s, s + k):
                spans[p] = a
    assert sorted(spans) == list(range(4000 - 99))
    again = raw[:500] + b"x" + raw[1000:1600]
    moved = {}
    for h, starts, n in sd.anchors(again):
        for a, s, k in zip(h.tolist(), starts.tolist(), n.tolist()):
            moved.update(dict.fromkeys(range(s, s + k), a))
    assert all(moved[p] == spans[p] for p in range(401)) and all(moved[p] == spans[p + 499] for p in range(501, 1002))


def rows_of(df):
    return sorted(((r["doc_id"], r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in df.collect()), key=str)


def test_whole_table(spark, sf):
    docs = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    assert rows_of(sd.op3_suffix_array(spark, sf)) == brute(docs)


def test_odd_rows(spark):
    draw = np.random.default_rng(7)
    p = ["".join(chr(97 + c) for c in draw.integers(0, 26, 150)) for _ in range(6)]
    rows = [(5, p[0] + p[1]), (2, p[1] + "é" * 120 + p[2]), (2, p[1] + "é" * 120 + p[2]), (None, p[3] + p[0][:99]), (None, None), (9, ""), (1, "a" * 700), (7, "ab" * 300 + p[3][:110])]
    rows += [(20 + i, p[4][i : 120 + i] + p[5][: 99 + i] + str(i)) for i in range(25)] + [(60, p[5] * 3), (61, p[1][20:]), (62, "\x00" * 250)]
    df = spark.createDataFrame([(*r, "clash", 1) for r in rows], "doc_id long, text string, start string, n int")
    assert rows_of(sd.repeats(df)) == brute(rows)
    cut = sd.remove_repeats(df)
    assert cut.columns == df.columns
    want = {x[4] for x in brute(rows)}
    assert all(hashlib.sha256((r["text"] or "").encode()).hexdigest() in want for r in cut.collect() if "é" not in (r["text"] or ""))
    assert sd.repeats(df.limit(0)).collect() == [] and sd.remove_repeats(df.limit(0)).collect() == []


def test_names_are_induced_alike_at_once_and_through_queues():
    draw = np.random.default_rng(21)
    for it in range(150):
        n, k = int(draw.integers(2, 200)), int(draw.integers(1, 12))
        names = draw.integers(0, k, n)
        if it % 4 == 0:
            names = np.tile(names[:3], 40)
        if it % 7 == 0:
            names = np.repeat(names[:9], 11)
        names = np.unique(names, return_inverse=True)[1].astype(np.int32)
        want = sorted(range(len(names)), key=lambda i: names[i:].tolist())
        for limit in (1 << 20, 0):
            assert induced_sort.sort_names(names, int(names.max()) + 1, induced_sort.Room(limit)).tolist() == want


def joined_of(contexts, limit):
    import pyarrow as pa

    joined = sd._Joined(limit)
    for at in range(0, len(contexts), 7):
        part = contexts[at : at + 7]
        about = np.asarray([np.arange(at, at + len(part)), np.zeros(len(part)), 10 * np.arange(at, at + len(part))], dtype=np.int64)
        joined.add(about, pa.array([b"", *part, b""], pa.binary()).slice(1, len(part)))
    return joined


@pytest.mark.parametrize("limit", [2_000, 1 << 24])
def test_a_shard_far_larger_than_memory(monkeypatch, limit):
    """Windows of contexts that earlier ones equal, against a set of all windows, with all of the sort on disk."""
    monkeypatch.setattr(induced_sort, "PIECE", 500)
    draw = np.random.default_rng(4)
    base = bytes(draw.integers(97, 101, 3_000).tolist())
    contexts = [base[a : a + n] for a, n in zip(draw.integers(0, 2_800, 90).tolist(), draw.integers(100, 180, 90).tolist())] + [b"q" * 170, b"q" * 150]
    room, seen, want = induced_sort.Room(limit), set(), set()
    for doc, c in enumerate(contexts):
        for p in range(len(c) - 99):
            if c[p : p + 100] in seen:
                want.add((doc, 10 * doc + p))
            seen.add(c[p : p + 100])
    got = set()
    for docs, _, starts, ends in sd.repeated_windows(joined_of(contexts, limit), 100, room):
        for d, s, e in zip(docs.tolist(), starts.tolist(), ends.tolist()):
            new = {(d, p) for p in range(s, e - 99)}
            assert not new & got
            got |= new
    assert got == want and bool(room.spilled) == (limit == 2_000)
    assert sum(map(len, contexts)) > 5 * 2_000


def test_an_anchor_that_everybody_shares_is_split(spark, monkeypatch):
    """A phrase with other text around it in each document, longer and shorter than a window, and some true repeats."""
    monkeypatch.setattr(sd, "HOT", 5)
    draw = np.random.default_rng(6)
    word = lambda n: "".join(chr(97 + c) for c in draw.integers(0, 26, n))
    short, long = word(60), word(130)
    rows = [(i, word(90) + short + word(40) + long + word(80)) for i in range(60)]
    rows += [(100 + i, rows[i][1][30:200]) for i in range(10)] + [(200, rows[3][1]), (None, long[:101]), (None, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    assert rows_of(sd.repeats(df)) == brute(rows)


@pytest.mark.parametrize("size", [300, 1000])
def test_small_shards_give_the_same(spark, monkeypatch, size):
    monkeypatch.setattr(sd, "SORTED", size)
    monkeypatch.setattr(sd, "WINDOWS", 37)
    draw = np.random.default_rng(9)
    base = "".join(chr(97 + c) for c in draw.integers(0, 26, 900))
    rows = [(i, base[a : a + 300] + str(i)) for i, a in enumerate(draw.integers(0, 600, 12).tolist())]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert rows_of(sd.repeats(df)) == brute(rows)


def test_rows_without_an_id_and_very_long_texts(spark):
    """Half of the rows have no id; their order is that of their texts' beginnings, and one text is long."""
    draw = np.random.default_rng(12)
    word = lambda n: "".join(chr(97 + c) for c in draw.integers(0, 26, n))
    shared = word(300)
    rows = [(None, f"{i:03}" + word(50) + shared[i : 150 + i]) for i in range(60)] + [(None, None)] * 5
    rows += [(3, word(120_000) + shared + word(120_000)), (4, shared + word(30)), (5, "ab" * 40_000)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(6)
    assert rows_of(sd.repeats(df)) == brute(rows)
