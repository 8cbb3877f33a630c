"""Values whose longest match is not valid, and phones without separators."""

import pytest

from blockfinder.llm import pii

CARD, IBAN = "4111111111111111", "DE89 3704 0044 0532 0130 00"


@pytest.mark.parametrize(
    ("text", "kind", "value"),
    [
        (f"{CARD} 123", "card", CARD),
        ("4111 1111 1111 1111 12/27", "card", "4111 1111 1111 1111"),
        (f"{IBAN} A1", "iban", IBAN),
        ("call +14155550100 now", "phone", "+14155550100"),
        ("+442079460018", "phone", "+442079460018"),
        ("41-111-1111-1113", "phone", "41-111-1111-1113"),
    ],
)
def test_what_is_valid_is_replaced(text, kind, value):
    text = f"a {text}"
    new, spans = pii.Pseudonyms(b"key").replace(text)
    start = text.index(value)
    assert spans == [(kind, start, start + len(value))]
    old, now = text[start : start + len(value)], new[start : start + len(value)]
    assert now != old and new[:start] == text[:start] and new[start + len(value) :] == text[start + len(value) :]
    make = pii.PATTERNS[kind][1]
    assert make(old, b"key", False) == now and make(now, b"key", True) == old


def test_country_codes_stay_and_nothing_valid_is_left_alone():
    assert pii.Pseudonyms(b"key").replace("+14155550100")[0][:2] == "+1"
    assert pii.Pseudonyms(b"key").replace("+442079460018")[0][:3] == "+44"
    assert pii.Pseudonyms(b"key").replace("+35312345678")[0][:4] == "+353"
    for text in ("4111111111111112", "31.06.2020", "+1234567"):
        assert pii.Pseudonyms(b"key").replace(text) == (text, [])
