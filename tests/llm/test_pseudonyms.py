import re
from datetime import date

import pytest

from rowsketch.llm import pseudonyms as P

TEXT = "Mail die.55@mail4.example.com or call +1 (017) 555-7713, card 4111 1111 1111 1111, account 9807915762804490, from 97.51.17.173 on 2021-03-04 (04.03.2021, 03/04/2021), ssn 123-45-6789, DE89 3704 0044 0532 0130 00 and token = \"04dbebab91ab85687d33eeaaf9ac699e1188f962\" TOKEN = \"9233A8ECF7C5B09FE5949719B6B82BC439E9329B\"."


@pytest.mark.parametrize("size", [2, 3, 10, 97, 1000])
def test_permutation(size):
    image = [P.permute(x, size, b"k", b"t") for x in range(size)]
    assert sorted(image) == list(range(size))
    assert [P.permute(y, size, b"k", b"t", undo=True) for y in image] == list(range(size))
    assert size < 97 or image != [P.permute(x, size, b"other", b"t") for x in range(size)]


def test_formats_are_kept_and_values_go():
    new, found = P.replace(TEXT, P.Pseudonyms())
    assert found == {"email": 1, "phone": 1, "card": 1, "number": 1, "ip": 1, "date": 3, "ssn": 1, "iban": 1, "secret": 2}
    for value in ("die.55@mail4.example.com", "555-7713", "4111 1111 1111 1111", "9807915762804490", "97.51.17.173", "2021-03-04", "123-45-6789", "3704 0044", "04dbebab", "9233A8EC"):
        assert value not in new
    shape = lambda s: re.sub(r"[0-9a-f]", "x", re.sub(r"[A-F]", "X", s))
    assert len(new.split()) == len(TEXT.split())
    card = re.search(r"card ([\d ]{19})", new).group(1).replace(" ", "")
    assert P.luhn_digit(card[:-1]) == card[-1]
    number = re.search(r"account (\d{16})", new).group(1)
    assert P.luhn_digit(number[:-1]) != number[-1]
    d = [int(x) for x in re.search(r"on (\d{4})-(\d\d)-(\d\d)", new).groups()]
    day = date(*d)
    assert f"({day:%d.%m.%Y}, {day:%m/%d/%Y})" in new
    assert shape(re.search(r'token = "(\w+)"', new).group(1)) == "x" * 40


def test_undo():
    new, _ = P.replace(TEXT, P.Pseudonyms(b"key"))
    assert P.replace(new, P.Pseudonyms(b"key", undo=True))[0] == TEXT


def test_equal_values_stay_linked():
    make = P.Pseudonyms()
    assert P.replace("a x.1@b.com b", make)[0].split()[1] == P.replace("x.1@b.com", make)[0]


@pytest.mark.parametrize("text", ["version 2.0. and 4.0.", "Chapter 3.1.4 of 1999", "999.1.1.1 and 2021-13-45", "price 12,345 in 2020", "deadbeef", "a" * 40, "12:30", "1 2 3 4 5"])
def test_ordinary_numbers_stay(text):
    assert P.replace(text, P.Pseudonyms()) == (text, {})


def test_spark(make, odd, none):
    got = {r["doc_id"]: r for r in P.pseudonymise(make([(1, TEXT), (2, "nothing")])).collect()}
    assert got[1]["n_date"] == 3 and got[1]["text"] == P.replace(TEXT, P.Pseudonyms())[0] and got[2]["text"] == "nothing"
    assert P.pseudonymise(odd).count() == odd.count() and P.pseudonymise(none).count() == 0
    assert {r["doc_id"]: r["text"] for r in P.pseudonymise(odd).collect()}[2] is None


def test_all_planted_values_go(documents):
    out = "\n".join(r["text"] for r in P.pseudonymise(documents).collect())
    for r in documents.collect():
        for value in re.findall(r"\S+@\S+\.com|(?<!\d)\d{16}(?!\d)|\+1 \(\d{3}\) \d{3}-\d{4}|\b[0-9a-f]{40}\b", r["text"]):
            assert value not in out


def iban_of(country, body):
    value = int("".join(str(int(c, 36)) for c in body + country + "00"))
    return f"{country}{98 - value % 97:02d}{body}"


def is_iban(s):
    return int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1


def is_card(s):
    return P.luhn_digit(s[:-1]) == s[-1]


AFTER = ["", " and go", " AND go", " WITH care", " IF SO", " 12/27", " 123", " cvc 999", ", OK", ".", " 4111 1111 1111 1111", " BE68 5390 0754 7034 x"]


@pytest.mark.parametrize("after", AFTER)
def test_ibans_beside_other_words(after):
    import random

    rng = random.Random(5)
    make = P.Pseudonyms()
    for country, length in P.IBAN_LENGTHS.items():
        flat = iban_of(country, "".join(rng.choice("0123456789") for _ in range(length - 4)))
        for s in (flat, " ".join(flat[k : k + 4] for k in range(0, length, 4))):
            alone = P.replace(s, make)[0]
            new, found = P.replace("pay " + s + after, make)
            assert new.startswith("pay " + alone) and found["iban"] >= 1, (s, after, new)
            assert alone != s and is_iban(alone.replace(" ", "")) and alone[:2] == country and len(alone) == len(s)
            assert P.replace(new, P.Pseudonyms(undo=True))[0] == "pay " + s + after


@pytest.mark.parametrize("after", AFTER)
def test_cards_beside_other_numbers(after):
    import random

    rng = random.Random(6)
    make = P.Pseudonyms()
    for groups in ((16,), (15,), (13,), (4, 4, 4, 4), (4, 6, 5), (4, 6, 4)):
        for gap in " -":
            for _ in range(40):
                body = "".join(rng.choice("0123456789") for _ in range(sum(groups) - 1))
                d = body + P.luhn_digit(body)
                at, parts = 0, []
                for g in groups:
                    parts.append(d[at : at + g])
                    at += g
                s = gap.join(parts)
                alone = P.replace(s, make)[0]
                new = P.replace("card " + s + after, make)[0]
                assert new.startswith("card " + alone) and is_card(re.sub(r"\D", "", alone)), (s, after, new)
                assert P.replace(new, P.Pseudonyms(undo=True))[0] == "card " + s + after


def test_nineteen_digits_in_groups():
    import random

    rng = random.Random(7)
    for _ in range(300):
        d = "".join(rng.choice("0123456789") for _ in range(19))
        s = f"{d[:4]} {d[4:8]} {d[8:12]} {d[12:16]} {d[16:]}"
        new, found = P.replace(s, P.Pseudonyms())
        assert sum(found.values()) == 1 and d[:16] != re.sub(r"\D", "", new)[:16]
        assert P.replace(new, P.Pseudonyms(undo=True))[0] == s
        if is_card(d[:16]):
            assert is_card(re.sub(r"\D", "", new)[:16]) and new.endswith(d[16:])
        elif is_card(d):
            assert is_card(re.sub(r"\D", "", new))
