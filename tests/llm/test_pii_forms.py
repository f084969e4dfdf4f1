import datetime
import re

import pytest

from densegrid.llm import pii

KEY = b"a key of the tests"


def days():
    first = datetime.date(1900, 1, 1).toordinal()
    return [datetime.date.fromordinal(first + k) for k in range(0, 73049)]


@pytest.mark.parametrize("look", ["{y:04}-{m:02}-{d:02}", "{d}/{m}/{y}", "{d:02}.{m:02}.{y}", "{m}/{d}/{y}"])
def test_dates_go_one_to_one_to_dates_of_their_look(look):
    """Every date of two centuries, brute force: as many pseudonyms as values, each in the value's own format."""
    texts = {look.format(y=t.year, m=t.month, d=t.day) for t in days()}
    out = {}
    for t in texts:
        m = pii._DATE.match(t)
        out[t] = pii._date(m, KEY)
    shape = lambda x: re.sub(r"\d", "9", x)
    assert all(shape(t) == shape(new) for t, new in out.items())
    assert len(set(out.values())) == len(texts)
    assert {t for t, new in out.items() if t == new} != texts


def test_every_small_number_has_a_pseudonym_of_its_own():
    for n in (1, 2, 3, 4):
        every = [str(k).zfill(n) for k in range(10**n)]
        assert {pii._number(x, KEY, "n") for x in every} == {*every}
    assert len({pii._ip(f"10.0.{a}.{b}", KEY) for a in range(40) for b in range(256)}) == 40 * 256


def test_masking_by_brute_force():
    """Every value of known places replaced by its own pseudonym, and nothing else changed."""
    values = {"email": ["jane.19@mail.example.com"], "ip": ["152.143.123.131", "2.0.0.1"], "card": ["4111 1111 1111 1111"], "phone": ["+1 (743) 555-3824", "(521) 555-6210", "212-555-1055", "+4915112345678"], "date": ["3/4/2021", "2021-02-28"], "hex": ["24be64439e3e49cf46b2d7c90f3602a3d0b907ff"]}
    alone = {v: pii.pseudonymise(v, KEY)[0] for vs in values.values() for v in vs}
    text = " and ".join(v + " is here" for v in alone)
    out, n = pii.pseudonymise(text, KEY)
    assert out == " and ".join(new + " is here" for new in alone.values()) and n == {k: len(v) for k, v in values.items()}
    assert len(set(alone.values())) == len(alone) and not set(alone) & set(alone.values())


def test_digit_groups_are_no_phone_numbers():
    for t in ("12 345 678 90", "in 10 20 30 40 parts", "1.234.567.89", "99.99.999", "scores 100-200-300", "10 000 000 000"):
        assert pii.pseudonymise(t, KEY) == (t, {})


def test_long_secrets_go_as_a_whole():
    for n in (40, 201, 256, 1000, 20_000):
        t = "key " + "a1B2" * (n // 4) + " end"
        out, found = pii.pseudonymise(t, KEY)
        assert sum(found.values()) == 1 and len(out) == len(t) and out[4:40] != t[4:40]


def test_blocks_of_long_secrets_stay_apart():
    """Secrets that share blocks get pseudonyms of their own, and a hex run stays one."""
    long = ["x9Y8z7" * 40 + end for end in ("a1", "a2", "b1")] + ["w" + "x9Y8z7" * 40 + "a1"]
    assert len({pii._word(x, KEY, "key") for x in long}) == len(long)
    hexes = ["0f" * 64, "0f" * 63 + "0e", "1f" + "0f" * 63]
    out = [pii._hex(x, KEY) for x in hexes]
    assert len(set(out)) == 3 and all(re.fullmatch("[0-9a-f]{128}", x) for x in out) and out[0][:64] == out[1][:64]


def test_a_run_with_many_digits_and_no_secret_is_gone_over_once():
    t = "1-" * 50_000
    assert pii.pseudonymise(t, KEY) == (t, {})
    t = "a-" * 50_000 + "1"
    assert pii.pseudonymise(t, KEY) == (t, {})


def test_a_key_is_required(spark):
    docs = spark.createDataFrame([(1, "x")], "doc_id bigint, text string")
    with pytest.raises(TypeError):
        pii.mask_documents(docs)
    with pytest.raises(ValueError):
        pii.mask_documents(docs, b"short")
