"""Secrets of any length."""

import pytest

from motifmill.llm.pii import redact, text_spans


@pytest.mark.parametrize("n", [8, 512, 513, 514, 5000, 200_000])
@pytest.mark.parametrize("quote", ['"', "'"])
def test_long_secrets_leave_the_text(n, quote):
    value = ("eyJhbGciOi." * (n // 10 + 1))[:n]
    text = f"before api_key = {quote}{value}{quote} after"
    at = text.index(value)
    assert text_spans(text) == [("secret", at, at + n)]
    assert redact(text, text_spans(text)) == f"before api_key = {quote}<SECRET>{quote} after"


@pytest.mark.parametrize("value", ["short12", "a" * 600 + " b", "a" * 600 + "\n", "a" * 600 + "\u2003"])
def test_short_values_and_white_space_are_no_secrets(value):
    assert text_spans(f'token="{value}"') == []


def test_a_value_without_its_quote_is_no_secret():
    assert text_spans('token="' + "a" * 600) == []
