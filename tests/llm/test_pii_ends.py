"""Personal data whose end is not the end of what looks like it."""

import pytest

from taskmesh.llm.pii import find_spans, masked

NUMBER = "DE89370400440532013000"


@pytest.mark.parametrize("number", [NUMBER, "DE89 3704 0044 0532 0130 00", "GB82 WEST 1234 5698 7654 32"])
@pytest.mark.parametrize("after", ["", " BIC COBADEFF", " EUR 50", " 12", ".", " and"])
def test_iban_before_upper_case_and_digits(number, after):
    text = f"IBAN {number}{after}"
    assert [(s, e) for k, s, e, _ in find_spans(text) if k == "iban"] == [(5, 5 + len(number))]


def test_search_goes_on_after_a_failure():
    text = f"bank AB12 CD34 {NUMBER} XY"
    assert [text[s:e] for k, s, e, _ in find_spans(text) if k == "iban"] == [NUMBER]
    assert not [s for s in find_spans("bank DE88370400440532013000 EUR 50") if s[0] == "iban"]


def test_secret_longer_than_128():
    token = "eyJ" + "aB3._-" * 200
    assert masked(f"token={token} end", find_spans(f"token={token} end")) == "token=[SECRET] end"
