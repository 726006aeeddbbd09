import hashlib
import random
import re

import pytest
from helpers import docs_frame, odd_texts

from bundlemv.llm import pii

# The base patterns as they are stated.
PLAIN = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def plain_base(text):
    out = []
    for kind, pattern in PLAIN.items():
        for m in re.finditer(pattern, text or ""):
            digits = re.sub("[^0-9]", "", m[0])
            ok = {
                "email": lambda: True, "ip": lambda: all(int(p) <= 255 for p in m[0].split(".")),
                "card": lambda: 16 <= len(digits) <= 19 and sum(sum(divmod(int(c) * (1 + i % 2), 10)) for i, c in enumerate(digits[::-1])) % 10 == 0,
                "phone": lambda: 8 <= len(digits) <= 15,
            }[kind]()
            if ok:
                out.append(f"{kind}:{m.start()}:{m.end()}")
    return out


def base_of(text):
    return [f"{k}:{s}:{e}" for k, s, e, _ in pii.find_spans(text) if k in PLAIN]


def test_base_against_stated_patterns():
    rng = random.Random(1)
    bits = ["@", ".", "a", "b-c", " ", "+", "1", "22", "255", "256", "-", "(", ")", "é", "4111111111111111", "x@y.z", "1.2.3.4", "+49 30 123456", "\n", "0001", "%_"]
    for _ in range(4000):
        text = "".join(rng.choice(bits) for _ in range(rng.randrange(25)))
        assert base_of(text) == plain_base(text), text


@pytest.mark.parametrize("text", ["a" * 200_000 + "@", "1" * 200_000 + ".1.1.", "+1" + " " * 200_000, "@" * 100_000, "1 " * 100_000])
def test_long_runs_take_linear_time(text):
    pii.find_spans(text)


def test_further_kinds():
    kinds = lambda t: [s[0] for s in pii.find_spans(t)]
    assert kinds("pay to DE89 3704 0044 0532 0130 00 now") == ["iban"]
    assert "iban" not in kinds("pay to DE89 3704 0044 0532 0130 01 now")
    assert kinds("my ssn is 123-45-6789") == ["ssn"] and kinds("part 123-45-6789") == [] and kinds("ssn 666-45-6789") == []
    plain, near = pii.find_spans("+49 30 1234567")[0][3], pii.find_spans("phone +49 30 1234567")[0][3]
    assert near > plain


def test_redaction():
    assert pii.redacted("mail a@b.cd or call +49 30 1234567!") == "mail <EMAIL> or call <PHONE>!"
    assert pii.redacted(None) is None and pii.redacted("clean") == "clean"
    assert "4111" not in pii.redacted("+4111111111111111x")


def test_query_against_plain_search(spark, tiny):
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{tiny}/documents.parquet").collect()}
    rows = pii.op5(spark, tiny).collect()
    assert len(rows) == len(texts)
    for r in rows:
        base = plain_base(texts[r.doc_id])
        assert r.base_sha256 == hashlib.sha256(",".join(base).encode()).hexdigest()
        assert [r.n_email, r.n_ip, r.n_card, r.n_phone] == [sum(x.startswith(k + ":") for x in base) for k in PLAIN]
        assert set(base) <= set(r.spans.split(",")) | {""}


def test_odd_inputs(spark):
    docs = docs_frame(spark, odd_texts() + ["a@b.cd"] * 2, ids=[*range(12), None, None])
    got = pii.detect(docs).collect()
    assert len(got) == 14 and [len(r.found) for r in got if r.doc_id is None] == [1, 1] and all(not r.found for r in got if r.doc_id is not None)
    clean = pii.redact(docs)
    assert clean.columns == docs.columns and clean.count() == 14
    assert pii.detect(docs.limit(0)).collect() == [] == pii.redact(docs.limit(0)).collect()


def test_secrets():
    token = "b44e15e09fd311c3cf3163b66d5a9875b883d8ce"
    kinds = lambda t: [(k, t[s:e]) for k, s, e, _ in pii.find_spans(t)]
    assert kinds(f'token = "{token}"') == [("secret", token)] == kinds(f"TOKEN: {token.upper()}".replace(token.upper(), token))
    assert kinds(f"commit {token} fixes it") == [] == kinds("token " + "ab1" * 20) == kinds("the key is aVeryLongWordWithoutAnyDigitInIt")
    assert kinds("-----BEGIN RSA PRIVATE KEY-----") == [("private_key", "-----BEGIN RSA PRIVATE KEY-----")]
    assert pii.redacted(f'api_key="{token}" x') == 'api_key="<SECRET>" x'
    assert pii.find_spans("key " + "aB3-" * 200_000) is not None
