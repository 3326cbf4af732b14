"""Personal data: the linear searches against the plain regular expressions, checksums, context and masking."""

import re

from hypothesis import given, settings
from hypothesis import strategies as st

from taskmesh.llm import pii

PLAIN = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def plain(text):
    out = []
    for kind in pii.BASE:
        for m in re.finditer(PLAIN[kind], text):
            digits = re.sub("[^0-9]", "", m.group())
            ok = {
                "email": lambda: True,
                "ip": lambda: all(int(x) <= 255 for x in m.group().split(".")),
                "card": lambda: 13 <= len(digits) <= 19 and pii.luhn(digits),
                "phone": lambda: 9 <= len(digits) <= 15,
            }[kind]()
            if ok:
                out.append((kind, *m.span()))
    return out


@settings(max_examples=600, deadline=None)
@given(st.text(alphabet="ab@.-+ 0123459()%é", max_size=60))
def test_base_spans_equal_plain_search(text):
    assert [s[:3] for s in pii.find_spans(text) if s[0] in pii.BASE] == plain(text)


def test_examples():
    text = "é a@b.co@c.d.e 1.2.3.4.5.6.7.8 300.1.1.1 4111 1111 1111 1111 +1 (988) 555-2485 999.1.2.3.4"
    assert [s[:3] for s in pii.find_spans(text) if s[0] in pii.BASE] == plain(text)


def test_checksums():
    assert pii.luhn("4111111111111111") and not pii.luhn("4111111111111112")
    assert pii.mod97("DE89370400440532013000") and not pii.mod97("DE88370400440532013000")


def test_added_kinds_need_checksum_or_context():
    assert ("iban", 5, 27) in [s[:3] for s in pii.find_spans("IBAN DE89370400440532013000 ok")]
    assert not [s for s in pii.find_spans("IBAN DE88370400440532013000 ok") if s[0] == "iban"]
    assert [s[0] for s in pii.find_spans("my account 12345678")] == ["account"]
    assert pii.find_spans("in total 12345678") == []
    assert [s[0] for s in pii.find_spans("password=66213754e9")] == ["secret"]


def test_long_runs_are_linear():
    assert pii.find_spans("a" * 300_000 + "1" * 300_000 + "+" * 1000) == []
    assert pii.find_spans("1." * 100_000 + "x") != []


def test_masking_keeps_the_rest():
    text = "write to a.b@c.de or +1 (988) 555-2485 now"
    assert pii.masked(text, pii.find_spans(text)) == "write to [EMAIL] or [PHONE] now"


def test_frames(spark):
    rows = [(1, "x a@b.co", "k"), (1, "x a@b.co", "k"), (None, None, None), (3, "", "k")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, spans string")
    assert sorted((r.doc_id or 0, len(r.spans)) for r in pii.scan(docs).collect()) == [(0, 0), (1, 1), (1, 1), (3, 0)]
    assert sorted((r.text or "", r.spans or "") for r in pii.redact(docs).collect()) == [("", ""), ("", "k"), ("x [EMAIL]", "k"), ("x [EMAIL]", "k")]
    assert pii.redact(docs.limit(0)).count() == 0
