"""Base spans against Python's re on the patterns as they are stated, and the disclosure measure on a small corpus."""

import hashlib
import math
import re


from unicat.llm import pii
from unicat.llm.queries import op6_pii

from .helpers import frame

STATED = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def luhn(d):
    t = 0
    for i, c in enumerate(reversed(d)):
        v = int(c) * (1 + i % 2)
        t += v - 9 if v > 9 else v
    return t % 10 == 0


def brute(text):
    out = []
    for n, (kind, p) in enumerate(STATED.items()):
        for m in re.finditer(p, text or ""):
            d = re.sub("[^0-9]", "", m[0])
            if {"email": True, "ip": all(int(x) <= 255 for x in m[0].split(".")) if kind == "ip" else True, "card": 12 <= len(d) <= 19 and luhn(d), "phone": 9 <= len(d) <= 15}[kind]:
                out.append((m.start(), n, m.end(), kind))
    return [f"{k}:{s}:{e}" for s, _, e, k in sorted(out)]


ODD = [
    None, "", "a@b.c@d.e_x@y.z", "ü😀 mail: Joe.B+x@Mail-1.Example.com., ip 1.2.3.4.5.6.7.8 and 256.1.1.1 and 0001.02.003.255",
    "4111 1111 1111 1111 4111-1111-1111-1111 4111  1111", "+1 (974) 555-3436, +49.30.1234567- +1 2 +999999999999999999", "@@a@b.co+1 555 555 5555",
    "1.2.3.4@5.6.7.8", "9" * 20000, "+1" + " " * 5000 + "2", ("x" * 3000 + " ") * 3 + "q@w.er", "79927398713 000000000000 1234567890123452", "a@b.c " * 1500, "12 " * 2000 + "5.5.5.5",
]


def check(df, rows):
    got = {r["__id"]: r["__base"] for r in df.collect()}
    for i, t in rows:
        assert [f"{pii.KINDS[s.kind]}:{s.start}:{s.end}" for s in got[i]] == brute(t), i


def test_base_spans_match_the_stated_patterns(spark):
    rows = list(enumerate(ODD))
    check(pii.base_spans(frame(spark, [(i, t, None, None, None) for i, t in rows])), rows)


def test_base_spans_of_the_given_documents(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = {r.doc_id: r for r in op6_pii(spark, sf).collect()}
    for r in docs.collect():
        want = brute(r.text)
        assert got[r.doc_id].base_sha256 == hashlib.sha256(",".join(want).encode()).hexdigest()
        assert set(want) <= set(got[r.doc_id].spans.split(",")) or not want
        assert got[r.doc_id].n_email == sum(x.startswith("email") for x in want)


def test_terms_that_disclose_an_entity(spark):
    rows = [(i, f"visit {i} of the treasurer Zanzibaro at boss@corp.example today number{i}x") for i in range(5)]
    rows += [(100 + i, f"today visit the treasurer at other{i}@x.example on day {i}") for i in range(20)]
    rows += [(200 + i, rows[0][1]) for i in range(50)]  # copies are one context
    rows += [(900, None), (None, "boss@corp.example and zanzibaro")]
    docs = frame(spark, [(i, t, None, None, None) for i, t in rows])
    terms = {(r["__entity"], r["__term"]): r["__bits"] for r in pii.disclosing_terms(docs.where("doc_id < 200")).collect()}
    assert terms == {("email:boss@corp.example", "zanzibaro"): 0.0}
    assert pii.disclosing_terms(docs.where("doc_id = 0 or doc_id >= 200")).count() == 0
    found = {r["__id"]: r["__all"] for r in pii.find(docs.where("doc_id < 200 or doc_id is null")).collect()}
    assert [s.kind for s in found[1]] == [4, 0] and rows[1][1][found[1][0].start : found[1][0].end] == "Zanzibaro"
    assert [s.kind for s in found[None]] == [0, 4] and [s.kind for s in found[105]] == [0]
    clean = {r.doc_id: r.text for r in pii.sanitise(docs.where("doc_id < 200")).collect()}
    assert clean[1] == "visit 1 of the treasurer  at [EMAIL] today number1x" and clean[100].startswith("today visit the treasurer at [EMAIL]")


def test_copies_do_not_hide_a_disclosing_term(spark, monkeypatch):
    texts = [f"visit {i} of the treasurer Zanzibaro at boss@corp.example today number{i}x" for i in range(3)]
    rows = [(100 * i + j, t) for i, t in enumerate(texts) for j in range(10)]
    rows += [(1000 + i, f"today visit the treasurer at other{i}@x.example on day {i}") for i in range(20)]
    docs = frame(spark, [(i, t, None, None, None) for i, t in rows])
    for bound in (pii.BROADCAST_ROWS, 0):
        monkeypatch.setattr(pii, "BROADCAST_ROWS", bound)
        terms = {(r["__entity"], r["__term"]): r["__bits"] for r in pii.disclosing_terms(docs).collect()}
        assert terms == {("email:boss@corp.example", "zanzibaro"): 0.0}
    # Three of its eight occurrences in distinct texts are beside the entity.
    rows = [(i, t) for i, t in rows if i < 1000] + [(2000 + i, f"zanzibaro alone {i % 5}") for i in range(50)]
    docs = frame(spark, [(i, t, None, None, None) for i, t in rows])
    bits = {r["__term"]: r["__bits"] for r in pii.disclosing_terms(docs, max_bits=9.0).collect()}
    assert abs(bits["zanzibaro"] + math.log2(3 / 8)) < 1e-9


def test_empty_table(spark):
    assert pii.find(frame(spark, [])).count() == 0
