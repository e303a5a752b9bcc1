"""Spans beyond the base kinds, with words on either side of them."""

import pytest

from semjoin.llm import pii


@pytest.mark.parametrize("text, kind, want", [
    ("AT61 1904 3002 3457 3201 EUR", "iban", "AT61 1904 3002 3457 3201"),
    ("AT61 1904 3002 3457 3201 is", "iban", "AT61 1904 3002 3457 3201"),
    ("ES9121000418450200051332 BANK", "iban", "ES9121000418450200051332"),
    ("AB12 CODE WORD AT61 1904 3002 3457 3201 EUR", "iban", "AT61 1904 3002 3457 3201"),
    ("123-45-6789 (SSN)", "national_id", "123-45-6789"),
    ("378282246310005 on my amex", "short_card", "378282246310005"),
])
def test_words_behind(text, kind, want):
    assert [text[a:b] for k, a, b, _ in pii.find(text) if k == kind] == [want]


def test_wrong_ibans_are_left():
    assert not [s for s in pii.find("AT62 1904 3002 3457 3201 EUR") if s[0] == "iban"]
