"""Cards and IBANs beside other digits and words."""

import pytest

from orderdep.llm import pseudonyms


@pytest.mark.parametrize(
    "before,value,behind,kind",
    [
        ("", "4111 1111 1111 1111", " 12/25", "card"),
        ("", "4111 1111 1111 1111", " 123", "card"),
        ("no 7 ", "4111-1111-1111-1111", "", "card"),
        ("20 ", "4111111111111111", " 12/25 123.", "card"),
        ("", "DE89 3704 0044 0532 0130 00", " EUR", "iban"),
        ("", "GB82 WEST 1234 5698 7654 32", " BIC WESTGB2L", "iban"),
        ("AB12 ", "CH93 0076 2011 6238 5295 7", ".", "iban"),
        ("", "DE89370400440532013000", " GB82 WEST", "iban"),
    ],
)
def test_values_beside_others(before, value, behind, kind):
    p = pseudonyms.Permuter(b"key")
    new, kinds = pseudonyms.replaced(before + value + behind, p)
    assert kinds == [kind]
    assert new.startswith(before) and new.endswith(behind) and value not in new and len(new) == len(before + value + behind)
    assert new[len(before) : len(before + value)] == pseudonyms.replaced(value, p)[0]


def test_digits_that_are_no_value_stay():
    p = pseudonyms.Permuter(b"key")
    for text in ("4111111111111112 x", "41111111111111111111111", "3.4111111111111111", "4111111111111111.5", "DE88 3704 0044 0532 0130 00 EUR"):
        assert pseudonyms.replaced(text, p) == (text, [])
