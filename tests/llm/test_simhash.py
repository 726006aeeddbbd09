import random

import numpy as np
import xxhash
from helpers import docs_frame, odd_texts

from bundlemv.llm import simhash


def plain_fingerprint(text):
    words = [w for w in "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "").replace("\t", " ").replace("\n", " ").replace("\r", " ").replace("\x0b", " ").replace("\x0c", " ").split(" ") if w]
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or [" ".join(words)]
    hs = [xxhash.xxh64_intdigest(s.encode(), seed=42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def plain_components(fps, reach=2):
    """fps: list of (id, fingerprint) -> {id: least reachable id}, by comparing all pairs."""
    up = {i: i for i, _ in fps}

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for a, (i, f) in enumerate(fps):
        for j, g in fps[:a]:
            if (f ^ g).bit_count() <= reach:
                x, y = root(i), root(j)
                up[max(x, y)] = min(x, y)
    return {i: root(i) for i in up}


def test_fingerprint():
    for t in odd_texts()[:8] + ["A B c D e", "x\x1fy z w", "É a b c É", "tab\tsep\x0bv\x0cf d"]:
        assert simhash.text_fingerprint(None if t is None else t.encode()) == plain_fingerprint(t)


def test_tree_finds_all_links():
    rng = random.Random(5)
    base = [rng.getrandbits(64) for _ in range(400)]
    fps = list(base)
    for f in base[:200]:
        for _ in range(6):
            f ^= 1 << rng.randrange(64)
            if rng.random() < 0.5:
                f ^= 1 << rng.randrange(64)
            fps.append(f)
    fps = np.array(sorted(set(fps)), dtype=np.uint64)
    want = plain_components(list(enumerate(map(int, fps))))
    for depth in (0, 3, 12):
        tree = simhash.build_tree(fps[::3], depth)
        forest, homes = simhash.Forest(len(fps)), np.zeros(len(fps), int)
        for _, at, home in simhash.deal(fps, tree, 2):
            homes[at[home]] += 1
            for i, j in simhash.link_within(fps[at], home, 2):
                forest.link(int(at[i]), int(at[j]))
        assert (homes == 1).all()
        assert {i: forest.root(i) for i in range(len(fps))} == want


def test_query_against_brute_force(spark, tiny):
    rows = simhash.op10(spark, tiny).collect()
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{tiny}/documents.parquet").collect()}
    assert {r.doc_id: r.fingerprint for r in rows} == {i: f"{plain_fingerprint(t):016x}" for i, t in texts.items()}
    assert {r.doc_id: r.component_id for r in rows} == plain_components([(r.doc_id, int(r.fingerprint, 16)) for r in rows])


def test_sharded_query(spark, monkeypatch):
    monkeypatch.setattr(simhash, "near_pairs_forest", lambda nodes, reach, f=simhash.near_pairs_forest: f(nodes, reach, shard_nodes=16))
    rng = random.Random(3)
    texts = []
    for i in range(150):
        words = [f"w{rng.randrange(4000)}" for _ in range(160)]
        for _ in range(1 + i % 4):
            texts.append(" ".join(words))
            words[rng.randrange(160)] = "changed"
    out = {r.doc_id: r for r in simhash.near_duplicate_components(docs_frame(spark, texts)).collect()}
    want = plain_components([(i, plain_fingerprint(t)) for i, t in enumerate(texts)])
    assert {i: r.component_id for i, r in out.items()} == want


def plain_similarity(a, b, shingle=5):
    sets = []
    for t in (a, b):
        w = t.lower().split()
        sets.append({tuple(w[i : i + shingle]) for i in range(max(1, len(w) - shingle + 1))} if w else set())
    return len(sets[0] & sets[1]) / max(1, len(sets[0] | sets[1]))


def test_similarity_links(spark, monkeypatch):
    rng = random.Random(8)
    passage = " ".join(f"p{i}" for i in range(60))
    texts, family = [], []
    for i in range(120):
        words = [f"w{rng.randrange(5000)}" for _ in range(rng.choice([40, 120, 400]))]
        texts.append(" ".join(words))
        family.append(i)
        for _ in range(i % 3):
            copy = list(words)
            for _ in range(max(1, len(words) // 100)):
                copy[rng.randrange(len(copy))] = f"x{rng.randrange(999)}"
            texts.append(" ".join(copy))
            family.append(i)
    for i in range(150):  # different texts that share a passage
        texts.append(passage + " " + " ".join(f"q{rng.randrange(9999)}" for _ in range(60)))
        family.append(1000 + i)
    for hot in (simhash.HOT_SEED, 20):
        monkeypatch.setattr(simhash, "HOT_SEED", hot)
        got = {r.doc_id: r.component_id for r in simhash.similar_components(docs_frame(spark, texts)).collect()}
        assert all(family[i] == family[c] for i, c in got.items())
        close = [(i, j) for i in range(len(texts)) for j in range(i) if family[i] == family[j] and plain_similarity(texts[i], texts[j]) >= 0.85]
        assert len(close) > 60 and sum(got[i] == got[j] for i, j in close) >= 0.97 * len(close)


def test_odd_inputs(spark):
    texts = odd_texts() + ["dup one two three"] * 2
    docs = docs_frame(spark, texts, ids=[*range(12), None, None])
    got = simhash.near_duplicate_components(docs).collect()
    assert len(got) == 14
    by = {r.doc_id: r for r in got if r.doc_id is not None}
    assert [by[i].component_id for i in (0, 1, 2)] == [0, 0, 0] and by[6].component_id == 5 == by[7].component_id
    kept = simhash.keep_one(docs)
    assert kept.columns == docs.columns
    ids = [r.doc_id for r in kept.collect()]
    assert 0 in ids and 1 not in ids and 6 not in ids and ids.count(None) == 2
    assert simhash.near_duplicate_components(docs.limit(0)).collect() == []


def test_similarity_is_exact(spark):
    rng = random.Random(17)
    texts = []
    for i in range(400):  # pairs at 800 of 1000 and at 799 of 1001 shingles
        same = 804 if i % 2 else 803
        for _ in range(2):
            texts.append(" ".join([f"w{i}a{k}" for k in range(same)] + [f"x{rng.getrandbits(60)}" for _ in range(904 - same)]))
    want = {k: k - 1 if k % 2 and k // 2 % 2 else k for k in range(len(texts))}
    assert plain_similarity(texts[2], texts[3]) == 0.8 and 0.798 < plain_similarity(texts[0], texts[1]) < 0.8
    assert {r.doc_id: r.component_id for r in simhash.similar_components(docs_frame(spark, texts)).collect()} == want


def test_unequal_repeats(spark):
    rng = random.Random(23)
    texts = []
    for i in range(60):  # few distinct lines; the second text repeats one of them many times
        lines = [" ".join(f"v{rng.getrandbits(60)}" for _ in range(20)) for _ in range(5)]
        texts += ["\n".join(lines), "\n".join(lines[:2] + [lines[2]] * 30 + lines[3:])]
    pairs = list(zip(texts[::2], texts[1::2]))
    assert all(plain_similarity(a, b) >= 0.8 for a, b in pairs)
    assert any((simhash.text_fingerprint(a.encode(), 5) ^ simhash.text_fingerprint(b.encode(), 5)).bit_count() > 20 for a, b in pairs)
    got = {r.doc_id: r.component_id for r in simhash.similar_components(docs_frame(spark, texts)).collect()}
    assert got == {k: k - k % 2 for k in range(len(texts))}


def test_hot_seed_is_no_key(spark, monkeypatch):
    monkeypatch.setattr(simhash, "HOT_SEED", 40)
    rng = random.Random(29)
    passage = " ".join(f"p{k}" for k in range(60))
    texts = []
    for i in range(100):  # pairs of near copies that all share a passage
        words = [f"q{rng.getrandbits(60)}" for _ in range(60)]
        texts += [passage + " " + " ".join(words), passage + " " + " ".join(words[:58] + ["end"])]
    got = {r.doc_id: r.component_id for r in simhash.similar_components(docs_frame(spark, texts)).collect()}
    assert got == {k: k - k % 2 for k in range(len(texts))}
    prints = simhash.sketches(docs_frame(spark, texts), 5, "doc_id", "text").withColumn("row", simhash.F.monotonically_increasing_id())
    keys = simhash.shard_keys(prints.select("node", "row", "size", "seeds", "sig"))
    assert max(r["count"] for r in keys.groupBy("key").count().collect()) <= 40
    copies = [f"{' '.join(f's{k}' for k in range(100))} t{i}" for i in range(90)]  # bands are frequent, too
    assert {r.component_id for r in simhash.similar_components(docs_frame(spark, copies)).collect()} == {0}


def test_near_fingerprints_meet(spark, monkeypatch):
    """Two texts without a common seed meet by their fingerprints; sets decide on texts whose fingerprints are near."""
    monkeypatch.setattr(simhash, "SEEDS", 1)
    rng = random.Random(4)
    for _ in range(5000):
        words = [f"w{rng.randrange(10**6)}" for _ in range(120)]
        texts = [" ".join(words), " ".join(words[:-3] + ["x", "y", "z"])]
        a, b = (simhash.shingle_set(t.encode(), 5) for t in texts)
        if simhash.distance(*(np.uint64(simhash.majority(h)) for h in (a, b))) <= 2 and simhash.signature(a)[0] != simhash.signature(b)[0]:
            break
    assert len(np.intersect1d(a, b)) / len(np.union1d(a, b)) >= 0.8
    assert {r.component_id for r in simhash.similar_components(docs_frame(spark, texts)).collect()} == {0}
    monkeypatch.setattr(simhash, "REACH", 64)
    far = [" ".join(words[:60] + [f"v{i}" for i in range(60)]), "one", None, ""]
    assert [r.component_id for r in simhash.similar_components(docs_frame(spark, texts + far)).orderBy("doc_id").collect()] == [0, 0, 2, 3, 4, 4]
