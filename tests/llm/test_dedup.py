"""Substring, exact, line and near-duplicate removal against brute force."""

import hashlib
import random
import re
import tracemalloc

import numpy as np
import pyarrow as pa
import xxhash

from cutfield.llm import exact_dedup, line_dedup, simhash, substring_dedup
from cutfield.llm.common import released, rows_at_once

WORD = re.compile(r"[^\x20\x09-\x0D]+")



def brute_substring(rows, window=20):
    """Smaller ids stand first; rows without an id behind all others; rows that share an id, or have none, are not before each other."""
    docs = [(i, float("inf") if i is None else i, WORD.findall(t or "")) for i, t in rows]
    least, out = {}, []
    for _, key, w in docs:
        for p in range(len(w) - window + 1):
            x = tuple(w[p : p + window])
            least[x] = min(least.get(x, key), key)
    for i, key, w in docs:
        gone, seen = set(), set()
        for p in range(len(w) - window + 1):
            x = tuple(w[p : p + window])
            if least[x] < key or x in seen:
                gone |= set(range(p, p + window))
            seen.add(x)
        kept = " ".join(x for k, x in enumerate(w) if k not in gone)
        out.append((i, len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest(), kept))
    return sorted(out, key=str)


def test_substring_random(spark):
    r = random.Random(3)
    passages = [[f"p{k}w{i}" for i in range(r.randint(15, 60))] for k in range(6)]
    rows = []
    for i in range(60):
        words = []
        for _ in range(r.randint(0, 6)):
            words += r.choice(passages)[r.randint(0, 5) :] if r.random() < 0.5 else [f"u{r.randint(0, 400)}" for _ in range(r.randint(1, 30))]
        rows.append((i, r.choice([" ", "\n", "  "]).join(words)))
    rows.append((60, " ".join(["same"] * 100)))
    got = substring_dedup.substring_dedup(spark.createDataFrame(rows, "doc_id long, text string"), chunk_bytes=3000)
    assert sorted((tuple(x) for x in got.collect()), key=str) == brute_substring(rows)
    again = substring_dedup.substring_dedup(spark.createDataFrame(rows, "doc_id long, text string"), chunk_bytes=500, bucket_bytes=900, seed=9)
    assert sorted((tuple(x) for x in again.collect()), key=str) == brute_substring(rows)


def thue_morse(n, flip):
    return "".join("ab"[(bin(i).count("1") + flip) % 2] for i in range(n))


def test_substring_hostile_words(spark):
    """Words on which every polynomial hash modulo 2**64 collides are told apart."""
    shared = " ".join(f"w{i}" for i in range(19))
    rows = [(k, f"{shared} {thue_morse(2048, k)}") for k in (0, 1)]
    got = {x["doc_id"]: x["n_removed"] for x in substring_dedup.substring_dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {0: 0, 1: 0}


def test_substring_null_and_repeated_ids(spark):
    line = " ".join(f"w{i}" for i in range(25))
    rows = [(None, line), (None, line), (4, line + " x"), (4, line + " x"), (9, "y " + line), (None, " ".join(f"n{i}" for i in range(22)))] * 3
    got = substring_dedup.substring_dedup(spark.createDataFrame(rows, "doc_id long, text string"), chunk_bytes=100, bucket_bytes=100).collect()
    assert sorted((tuple(x) for x in got), key=str) == brute_substring(rows)


def test_substring_collision_is_an_error(spark, monkeypatch):
    """A run that does not stand where a hash says it starts stops the job."""
    import pyarrow as pa
    import pytest

    docs = pa.table({"doc_id": [1], "body": [" ".join(map(str, range(30)))], "chunk": [0]})
    run = lambda words: pa.table({"chunk": [0], "owner": [1], "body": [" ".join(words).encode()]})
    check = substring_dedup._check(20)
    assert not check(docs, run(map(str, range(3, 25)))).num_rows
    with pytest.raises(ValueError):
        check(docs, run([*map(str, range(3, 24)), "x"]))


def test_substring_packing():
    r = np.random.default_rng(5)
    for size, top in ((0, 10), (1, 1 << 30), (1000, 1 << 27), (50, 1 << 27), (5000, 20_000)):
        x = np.unique(r.integers(0, top, size))
        assert (substring_dedup._unpack(substring_dedup._pack(x)) == x).all()
    assert substring_dedup._unpack(substring_dedup._pack(np.array([65535, 131070, 131071]))).tolist() == [65535, 131070, 131071]


def test_substring_edges(edge, empty):
    rows = [(x["doc_id"], x["text"]) for x in edge.select("doc_id", "text").collect()]
    got = sorted((tuple(x) for x in substring_dedup.substring_dedup(edge).collect()), key=str)
    assert got == brute_substring(rows)
    assert substring_dedup.substring_dedup(empty).count() == 0


def test_exact_edges(edge, empty):
    got = {(x["doc_id"], x["text_sha256"]): x for x in exact_dedup.exact_dedup(edge).collect()}
    assert len(exact_dedup.exact_dedup(edge).collect()) == edge.count()
    by_id = {k[0]: v for k, v in got.items()}
    assert by_id[6]["keep_id"] == 1 and not by_id[6]["kept"] and by_id[6]["group_size"] == 2
    assert by_id[3]["keep_id"] == 2 and by_id[2]["group_size"] == 2 and by_id[2]["kept"]
    assert by_id[5]["group_size"] == 2 and by_id[5]["kept"]
    assert by_id[12]["keep_id"] == 7
    top = {x["doc_id"]: x for x in exact_dedup.exact_dedup(edge, keep="largest").collect()}
    assert top[1]["keep_id"] == 6 and top[7]["keep_id"] == 12
    assert exact_dedup.exact_dedup(empty).count() == 0


def test_exact_splits_collisions(spark, monkeypatch):
    """With a hash that always collides, bytes still tell groups apart."""
    from pyspark.sql import functions as F

    monkeypatch.setattr(exact_dedup.F, "md5", lambda c: F.lit("00" * 16))
    rows = [(1, "a"), (2, "b"), (3, "A"), (4, "c"), (5, "b"), (6, "a")]
    got = {x["doc_id"]: (x["keep_id"], x["group_size"], x["kept"]) for x in exact_dedup.exact_dedup(spark.createDataFrame(rows, "doc_id long, text string"), rows_per_salt=2).collect()}
    monkeypatch.undo()
    assert got == {1: (1, 3, True), 3: (1, 3, False), 6: (1, 3, False), 2: (2, 2, True), 5: (2, 2, False), 4: (4, 1, True)}


def test_exact_hot_group(spark):
    rows = [(i, "hot" if i % 3 else f"t{i}") for i in range(3000)]
    got = exact_dedup.exact_dedup(spark.createDataFrame(rows, "doc_id long, text string"), rows_per_salt=64).collect()
    hot = [x for x in got if x["doc_id"] % 3]
    assert len(got) == 3000 and {x["group_size"] for x in hot} == {2000} and sum(x["kept"] for x in hot) == 1


def brute_lines(rows, span=3):
    seen, out = set(), []
    for i, t in sorted(rows):
        lines = t.split("\n")
        gone = set()
        for p in range(len(lines) - span + 1):
            win = tuple(lines[p : p + span])
            if not WORD.search("\n".join(win)):
                continue
            if win in seen:
                gone |= set(range(p, p + span))
            seen.add(win)
        out.append((i, len(lines), len(gone), "\n".join(x for k, x in enumerate(lines) if k not in gone)))
    return out


def test_lines_random(spark):
    r = random.Random(4)
    rows = [(i, "\n".join(r.choice(["a", "b", "c d", "", " ", "e"]) for _ in range(r.randint(0, 12)))) for i in range(150)]
    got = line_dedup.line_dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted(tuple(x) for x in got) == brute_lines(rows)


def test_lines_edges(edge, empty):
    out = line_dedup.line_dedup(edge).collect()
    assert len(out) == edge.count()
    got = {x["doc_id"]: x for x in out}
    assert got[7]["n_removed"] == 0 and got[8]["n_removed"] == 3 and got[8]["text"] == "head\nend" and got[12]["text"] == ""
    assert got[2]["n_lines"] == 1 and got[None]["n_removed"] == 0
    whole = line_dedup.remove_lines(edge)
    assert whole.columns == edge.columns and whole.count() == edge.count()
    assert whole.where("text is null").count() == 1
    assert line_dedup.line_dedup(empty).count() == 0 and line_dedup.remove_lines(empty).count() == 0


def brute_fingerprint(text):
    w = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not w:
        return 0
    s = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else [" ".join(w)]
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_components(values, radius=3):
    root = {v: v for v in values}

    def find(v):
        while root[v] != v:
            v = root[v]
        return v

    vs = sorted(values)
    for i, a in enumerate(vs):
        for b in vs[i + 1 :]:
            if (a ^ b).bit_count() <= radius:
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {v: find(v) for v in values}


def test_simhash_edges(edge, empty):
    rows = [(x["doc_id"], x["text"]) for x in edge.select("doc_id", "text").collect()]
    got = [tuple(x) for x in simhash.simhash_groups(edge).collect()]
    fps = {i: brute_fingerprint(t) for i, t in rows}
    comp = brute_components(set(fps.values()))
    least = {}
    for i, f in fps.items():
        if i is not None:
            least[comp[f]] = min(least.get(comp[f], i), i)
    assert sorted(got, key=str) == sorted([(i, f"{fps[i]:016x}", least.get(comp[fps[i]])) for i, _ in rows], key=str)
    kept = simhash.simhash_dedup(edge)
    assert kept.columns == edge.columns and {x["doc_id"] for x in kept.collect()} == {*least.values()} | ({None} if comp[fps[None]] not in least else set())
    assert simhash.simhash_groups(empty).count() == 0 and simhash.simhash_dedup(empty).count() == 0


def test_simhash_links_are_complete(spark):
    """Every pair within the radius is connected, odd and even radius, dense balls included."""
    r = random.Random(5)
    for radius in (2, 3):
        values = set()
        for _ in range(12):
            c = r.getrandbits(64)
            for _ in range(25):
                x = c
                for b in r.sample(range(64), r.randint(0, 4)):
                    x ^= 1 << b
                values.add(x)
        signed = [(int(np.uint64(v).astype(np.int64)),) for v in values]
        edges = simhash.links(spark.createDataFrame(signed, "fp long"), radius=radius)
        roots = {x["node"]: x["root"] for x in simhash.components(edges).collect()}
        want = brute_components(values, radius)
        groups, seen = {}, {}
        for v in values:
            s = int(np.uint64(v).astype(np.int64))
            groups.setdefault(want[v], set()).add(v)
            seen.setdefault(roots.get(s, s), set()).add(v)
        assert sorted(map(sorted, groups.values())) == sorted(map(sorted, seen.values()))


def test_forest_of_a_large_group():
    r = random.Random(6)
    base = r.getrandbits(64)
    values = set()
    while len(values) < 2500:
        x = base
        for b in r.sample(range(64), r.randint(0, 5)):
            x ^= 1 << b
        values.add(x)
    fps = np.array(sorted(values), np.uint64)
    want = brute_components_np(fps)
    parent = {int(v): int(v) for v in fps}

    def find(v):
        while parent[v] != v:
            v = parent[v]
        return v

    for a, b in simhash._forest(fps, 3):
        assert (a ^ b).bit_count() <= 3
        x, y = find(a), find(b)
        parent[max(x, y)] = min(x, y)
    assert len({find(int(v)) for v in fps}) == want


def brute_components_np(fps):
    left, n = set(range(len(fps))), 0
    while left:
        stack = [left.pop()]
        n += 1
        while stack:
            i = stack.pop()
            near = [j for j in np.flatnonzero(np.bitwise_count(fps ^ fps[i]) <= 3).tolist() if j in left]
            left.difference_update(near)
            stack += near
    return n


def brute_grams(text, size=5):
    w = [x.translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")) for x in WORD.findall(text or "")]
    return {tuple(w[p : p + size]) for p in range(max(1, len(w) - size + 1))}


def brute_near(texts, similarity=0.8):
    """For each id, the smaller ids whose shingles are similar enough."""
    sets = {i: brute_grams(t) for i, t in sorted(texts.items())}
    ids = list(sets)
    return {j: [i for i in ids if i < j and len(sets[i] & sets[j]) >= similarity * len(sets[i] | sets[j])] for j in ids}


def check_near(texts, kept, least=0.75):
    """Whatever goes has a similar document before it; copies all go, and most others that have one before them: a fingerprint of 64 bits does not catch every pair near the threshold."""
    before = brute_near(texts)
    assert all(before[i] for i in texts if i not in kept)
    due = [i for i in texts if before[i]]
    copies = [i for i in due if any(brute_grams(texts[i]) == brute_grams(texts[j]) and len(WORD.findall(texts[i] or "")) == len(WORD.findall(texts[j] or "")) for j in before[i])]
    assert not [i for i in copies if i in kept and any(WORD.findall((texts[i] or "").lower()) == WORD.findall((texts[j] or "").lower()) for j in before[i])]
    assert sum(i not in kept for i in due) >= least * len(due)


def test_near_dedup(spark):
    r = random.Random(12)
    vocabulary = [f"w{i}" for i in range(3000)]
    texts, n = {}, 0
    for _ in range(60):
        base = [r.choice(vocabulary) for _ in range(r.randint(120, 400))]
        for _ in range(r.randint(1, 5)):
            words = base.copy()
            for _ in range(r.randint(0, 3)):
                words[r.randrange(len(words))] = r.choice(vocabulary)
            texts[n] = " ".join(words)
            n += 1
        shuffled = base.copy()
        r.shuffle(shuffled)
        texts[n] = " ".join(shuffled)  # the same words in another order: the fingerprint is equal, the text is another one
        n += 1
    texts |= {n: "", n + 1: None, n + 2: "one two", n + 3: "One TWO", n + 4: "two one"}
    df = spark.createDataFrame([(i, t, "x") for i, t in texts.items()], "doc_id long, text string, c0 string")
    got = simhash.near_dedup(df)
    assert got.columns == df.columns
    check_near(texts, {x["doc_id"] for x in got.collect()})


def test_near_dedup_edges(edge, empty, spark):
    out = simhash.near_dedup(edge)
    kept = sorted((x["doc_id"] for x in out.collect()), key=str)
    assert out.columns == edge.columns and None in kept and 6 not in kept and 12 not in kept
    # 5 shares 16 of 18 shingles with 1, and 8 shares 8 of 10 with 7
    assert set(kept) == {1, 2, 7, 9, 10, 11, None}
    assert simhash.near_dedup(edge.where("doc_id <> 1 or doc_id is null")).where("doc_id = 5").count() == 2
    assert simhash.near_dedup(empty).count() == 0


def test_weighted_fingerprint():
    words = ["a"] * 8 + ["b"] * 3 + ["c", "d"]
    values = {w: xxhash.xxh64_intdigest(w.encode(), 42) for w in set(words)}
    weight = {w: round(64 * (1 + np.log(words.count(w)))) for w in set(words)}
    want = sum(1 << b for b in range(64) if 2 * sum(weight[w] for w in values if values[w] >> b & 1) > sum(weight.values()))
    assert simhash.weighted_fingerprint([w.encode() for w in words]) == want and simhash.weighted_fingerprint([]) == 0


def _brute_kept(texts):
    return {i for i, b in brute_near(texts).items() if not b}


def test_near_dedup_loses_no_pair(spark):
    """Every document with a similar one before it goes, and no other: pairs at the threshold, whatever their fingerprints."""
    r = random.Random(5)
    texts, n = {}, 0
    for _ in range(120):
        base = [f"w{r.randrange(5000)}" for _ in range(r.randint(12, 90))]
        for _ in range(4):
            words = base.copy()
            for _ in range(r.randint(0, 2)):
                words[r.randrange(len(words))] = f"w{r.randrange(5000)}"
            texts[n] = " ".join(words[r.randint(0, 3) :])
            n += 1
    ids = list(texts)
    r.shuffle(ids)
    texts = dict(zip(ids, texts.values()))
    want = _brute_kept(texts)
    got = simhash.near_dedup(spark.createDataFrame(list(texts.items()), "doc_id long, text string"))
    assert {x["doc_id"] for x in got.collect()} == want and len(want) < n


def test_near_dedup_large_group(spark, monkeypatch):
    """Many near copies of one text, similar to it and mostly not to each other, and a passage that many unlike texts share."""
    r = random.Random(6)
    base = [f"b{i}" for i in range(60)]
    texts = {}
    for i in range(150):
        words = base.copy()
        words[r.randrange(5, 55)] = f"x{i}"
        texts[i] = " ".join(words)
    texts[70] = " ".join(base)
    for i in range(150, 250):
        texts[i] = " ".join(base[:30] + [f"y{r.randrange(10**6)}" for _ in range(40)])
    monkeypatch.setattr(simhash, "BLOCK", 64)  # several blocks
    want = _brute_kept(texts)
    got = simhash.near_dedup(spark.createDataFrame(list(texts.items()), "doc_id long, text string"))
    assert {x["doc_id"] for x in got.collect()} == want and 20 < len(want) < 250


def test_near_dedup_holds_no_second_copy_of_a_batch(spark):
    """Comparing the pairs of a batch takes little memory beside it; what Spark hands over at once is bounded while they run."""
    sets = np.arange(2000 * 1000, dtype=np.uint64).reshape(2000, 1000)
    grams = pa.array([s.tobytes() for s in sets], pa.binary())
    pairs = pa.record_batch([pa.array(range(2000)), grams, grams], names=["x", "mine", "theirs"])
    side = pa.StructArray.from_arrays([pa.array(range(2000)), pa.array(range(2000)), grams], names=["num", "least", "grams"])
    lists = pa.ListArray.from_arrays(pa.array(range(0, 2001, 20), pa.int32()), side)
    blocks = pa.record_batch([lists.slice(1), lists.slice(0, 99)], names=["mine", "theirs"])
    for run, batch, want in ((simhash._similar(0.8), pairs, list(range(2000))), (simhash._blocks_similar(0.8), blocks, [])):
        tracemalloc.start()
        got = [n for b in run([batch]) for n in b.column("num").to_pylist()]
        peak = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
        assert got == want and peak < batch.nbytes / 4
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    was = spark.conf.get(key)
    with rows_at_once(spark, 7):
        sizes = [r["n"] for r in spark.range(100).mapInArrow(lambda bs: (pa.record_batch([pa.array([b.num_rows])], names=["n"]) for b in bs), "n long").collect()]
    assert max(sizes) <= 7 and sum(sizes) == 100 and spark.conf.get(key) == was


def test_near_dedup_hands_over_few_texts_at_once(spark, monkeypatch):
    """No Python step of the stage gets more than 4096 rows at once, nor more than 1024 texts."""

    def watched(name, most):
        make = getattr(simhash, name)

        def made(*args):
            inner = make(*args)

            def run(batches):
                def checked():
                    for batch in batches:
                        assert batch.num_rows <= most
                        yield batch

                return inner(checked())

            return run

        monkeypatch.setattr(simhash, name, made)

    watched("_marks", 1024)
    watched("_prefixes", 4096)
    watched("_meetings", 4096)
    docs = spark.range(9000).selectExpr("id as doc_id", "concat_ws(' ', transform(sequence(1, 12), i -> concat('w', id, '-', i))) as text").coalesce(1)
    assert simhash.near_dedup(docs).count() == 9000


def test_near_dedup_shared_passages_make_no_pairs(spark, monkeypatch):
    """Texts that share a passage, and little else, meet nowhere: shingles of a few texts stand behind those of one."""
    r = random.Random(15)
    texts = {}
    for i in range(84):
        passage = [f"p{i % 12}-{j}" for j in range(20)]
        texts[i] = " ".join(passage + [f"w{r.randrange(10**9)}" for _ in range(80)])
    make = simhash._meetings

    def made(*args):
        def run(batches):
            for batch in make(*args)(batches):
                assert batch.num_rows == 0
                yield batch

        return run

    monkeypatch.setattr(simhash, "_meetings", made)
    assert simhash.near_dedup(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).count() == 84


def test_released_worker_holds_little(spark):
    """After a step that took much memory in small pieces, a worker's memory is handed back; it would stay with it otherwise."""

    def held(run):
        def resident(batches):
            for batch in batches:
                with open("/proc/self/statm") as f:
                    yield pa.record_batch([pa.array([int(f.read().split()[1]) * 4096 + 0 * batch.num_rows])], names=["n"])

        one = spark.range(1).coalesce(1)
        one.mapInArrow(run, "n long").collect()
        return one.mapInArrow(resident, "n long").first()["n"]

    def pieces(batches):
        for batch in batches:
            wide, last = [bytes(50_000) for _ in range(6000)], bytes(50_000)  # a small piece at the end keeps the heap from shrinking by itself
            wide.clear()
            yield pa.record_batch([pa.array([len(last)])], names=["n"])

    calm = held(released(lambda batches: (pa.record_batch([pa.array([b.num_rows])], names=["n"]) for b in batches)))
    assert held(released(pieces)) < calm + 100_000_000
