"""Cards and IBANs with digits or capitals after them."""

import random

from tuneloom.llm import pseudonyms


def test_numbers_followed_by_others():
    p = pseudonyms.Pseudonymiser(b"key")
    card, iban = p("4111 1111 1111 1111")[0], p("BE68 5390 0754 7034")[0]
    for tail in ("", " 123", " 12/27", "-12", " 999", ", 5"):
        assert p("pay 4111 1111 1111 1111" + tail)[0] == f"pay {card}{tail}"
    for i in range(1000):  # one in ten makes a longer valid number by chance
        assert p(f"4111 1111 1111 1111 {i:03}")[0] == f"{card} {i:03}"
    for tail in (" BIC KREDBEBB", " ABCD", " EUR", ""):
        assert p("BE68 5390 0754 7034" + tail)[0] == iban + tail
    assert p("77 4111 1111 1111 1111")[0] == f"77 {card}"


def test_round_trip_of_neighbours():
    p, rng = pseudonyms.Pseudonymiser(b"key"), random.Random(5)
    for _ in range(2000):
        n = rng.choice([16, 19])
        body = "4" + "".join(rng.choice("0123456789") for _ in range(n - 2))
        digits = next(body + c for c in "0123456789" if pseudonyms.luhn(body + c))
        text = " ".join(digits[i : i + 4] for i in range(0, n, 4)) + rng.choice(["", " 123", " 12/27", " x"])
        assert p(p(text)[0], True)[0] == text
