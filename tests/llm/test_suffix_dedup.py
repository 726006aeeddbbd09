import hashlib
import random
from collections import Counter

import numpy as np
import pytest
from helpers import docs_frame, odd_texts

from bundlemv.llm import suffix_dedup as sd


def plain_removed(texts, length=400):
    """Per text the bytes (as flags) covered by a window that occurs more than once."""
    seen = Counter(t[i : i + length] for t in texts for i in range(len(t) - length + 1))
    out = []
    for t in texts:
        flags = np.zeros(len(t), bool)
        for i in range(len(t) - length + 1):
            if seen[t[i : i + length]] > 1:
                flags[i : i + length] = True
        out.append(flags)
    return out


def digest_rows(texts):
    rows = []
    for t, flags in zip(texts, plain_removed(texts)):
        runs = int((np.diff(np.concatenate([[0], flags.astype(np.int8)])) == 1).sum())
        rows.append((len(t), int(flags.sum()), runs, hashlib.sha256(bytes(np.frombuffer(t, np.uint8)[~flags])).hexdigest()))
    return rows


def got_rows(out):
    rows = []
    for r in out.collect():
        removed = sum(s.end - s.start for s in r.removed)
        rows.append((r.doc_id, (r.n_bytes, removed, len(r.removed), hashlib.sha256(r.kept).hexdigest())))
    return rows


def planted(seed, n=60):
    rng = random.Random(seed)
    words = lambda k: " ".join(rng.choice("abcdefghijklmnopqrst") * rng.randrange(1, 9) + str(rng.randrange(999)) for _ in range(k))
    passages = [words(60)[: rng.choice([399, 400, 401, 430, 900])] for _ in range(6)]
    texts = []
    for i in range(n):
        t = words(rng.randrange(300))
        for _ in range(rng.randrange(3)):
            at = rng.randrange(len(t) + 1)
            t = t[:at] + rng.choice(passages) + t[at:]
        texts.append(t)
    near = list(texts[0] * 3)
    near[500:501] = "#"
    periodic = "ab c" * 300
    return [*texts, texts[1], texts[1], "".join(near), "=" * 1500, "=" * 420, periodic, "x" + periodic, "é" * 450]


@pytest.mark.parametrize("seed,hot,slab", [(0, 4096, 1 << 20), (1, 2, 1 << 20), (2, 4096, 700)])
def test_against_all_windows(spark, seed, hot, slab, monkeypatch):
    texts = planted(seed)
    # slabs are read where workers import the module, so a small one is tried without Spark
    if slab != sd.SLAB:
        monkeypatch.setattr(sd, "SLAB", slab)
        data = [t.encode() for t in texts]
        stretches = Counter()
        for t in data:
            covered = np.zeros(max(0, len(t) - 399), int)
            for kind, _, _, lo, hi, _ in sd.suffixes(t, 400):
                for a, b in zip(lo, hi):
                    if kind == 0:
                        covered[a : b + 1] += 1
                    stretches[kind] += b - a + 1
            assert (covered == 1).all()
        assert stretches[0] == sum(stretches[k] for k in (1, 2, 3, 4))
        return
    docs = docs_frame(spark, texts).repartition(7)
    want = digest_rows([t.encode() for t in texts])
    got = dict(got_rows(sd.deduplicated(docs, hot=hot)))
    assert [got[i] for i in range(len(texts))] == want


def test_family_counts_like_a_binary_number(spark):
    texts = planted(3, 40)
    docs = docs_frame(spark, texts)
    family = sd.SuffixFamily(spark, 3)
    for i in range(5):
        family.insert(docs.where(f"doc_id % 5 = {i}"))
        assert [x is not None for x in family.levels] == [bool(i + 1 >> b & 1) for b in range((i + 1).bit_length())]
    once = sd.SuffixFamily(spark, 3)
    once.insert(docs)
    assert {r.key for r in family.matches().collect()} == {r.key for r in once.matches().collect()}


def test_query_against_all_windows(spark, tiny):
    texts = {r.doc_id: (r.text or "").encode() for r in spark.read.parquet(f"{tiny}/documents.parquet").collect()}
    ids = sorted(texts)
    want = dict(zip(ids, digest_rows([texts[i] for i in ids])))
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in sd.op2(spark, tiny).collect()}
    assert got == want and any(v[1] for v in want.values())


def plain_strings(text):
    """Per row the strings of 32 words with the least hash of 19 neighbours, as tuples."""
    words, chosen = text.split(), set()
    strings = [tuple(words[i : i + 32]) for i in range(len(words) - 31)]
    for i in range(len(strings) - 18):
        chosen.add(min(strings[i : i + 19], key=lambda s: one_hash(s)))
    return chosen


def one_hash(s, known={}):
    """The hash by which a string of 32 words is chosen, with Python's integers."""
    if s not in known:
        word = lambda w: int(sd._mixed(np.array([sum(int(sd._LETTERS[0][b]) * pow(sd._BASE, i, 1 << 64) for i, b in enumerate(w)) % (1 << 64)], np.uint64))[0])
        h = 0
        for w in s:
            h = (h * sd._BASE + word(w)) % (1 << 64)
        known[s] = int(sd._mixed(np.array([h], np.uint64))[0])
    return known[s] >> 24


def test_passages_in_words(spark, monkeypatch):
    rng = random.Random(7)
    words = lambda n: " ".join(rng.choice("abcdefgh") * rng.randrange(1, 4) + str(rng.randrange(99)) for _ in range(n))
    passage, line, blank = words(50), words(31), words(80)
    texts = [words(rng.randrange(49, 200)) for _ in range(30)]
    texts[3], texts[8] = texts[3] + " " + passage + "\n" + words(9), passage
    texts[5], texts[9] = texts[5] + " " + line + " " + words(60), words(60) + "\n" + line
    texts[11], texts[12] = blank, blank.replace(" ", "\n ")
    texts[13] = " ".join([words(60)] * 3)  # repeats itself only
    drawn = [plain_strings(t.encode()) for t in texts]
    seen = Counter(s for x in drawn for s in x)
    want = [sum(seen[s] > 1 for s in x) for x in drawn]
    got = {r.doc_id: r.n_shared for r in sd.deduplicated(docs_frame(spark, texts)).collect()}
    assert [got[i] for i in range(30)] == want
    assert {i for i, n in enumerate(want) if n} == {3, 8, 11, 12}
    whole = sd.word_strings(texts[3].encode())
    monkeypatch.setattr(sd, "BLOCK", 7)
    assert (sd.word_strings(texts[3].encode()) == whole).all() and (sd.word_strings(texts[3].encode(), sd.whole_prints(texts[3].encode())) == whole).all()


def test_odd_inputs(spark):
    long = "x y z " * 100
    texts = [*odd_texts()[:8], long, long, long]
    docs = docs_frame(spark, texts, ids=[*range(9), None, None])
    got = got_rows(sd.deduplicated(docs))
    want = digest_rows([(t or "").encode() for t in texts])
    key = lambda x: (x[0] is None, x[0] or 0, x[1])
    assert sorted(got, key=key) == sorted(zip([*range(9), None, None], want), key=key)
    assert sd.deduplicated(docs.limit(0)).collect() == []
