"""Surrogates: names without their title, scripts, long entities, check digits, and one-to-one over a whole table by both plans."""

import random
import re

import pytest

from cellcluster.llm import surrogates

WORD = r"[^\W\d_]+"


def rewritten(spark, texts, key="key", extra=()):
    df = spark.createDataFrame([(k, t, *("x" for _ in extra)) for k, t in enumerate(texts)], "doc_id bigint, text string" + "".join(f", `{c}` string" for c in extra))
    return [r for r in sorted(surrogates.pseudonymise(df, key).collect(), key=lambda r: r.doc_id)]


def test_names_stay_one_person_without_their_title(spark):
    a, b, c, d = (r.text for r in rewritten(spark, [
        "Mr John Smith met Mr Smith. Later John Smith left. Dr A + 60 x b", "Ms JANE DOE and Ms Jane Doe; Jane Doe", "Mr Jan van der Berg, Jan van der Berg", "John Smith is not announced here",
    ]))
    m = re.fullmatch(rf"Mr ({WORD}) ({WORD}) met Mr ({WORD})\. Later ({WORD}) ({WORD}) left\. Dr A \+ 60 x b", a)
    assert m[1] == m[4] and m[2] == m[3] == m[5] and m[1] in surrogates.GIVEN["m", "Latin"] and "Smith" not in a
    m = re.fullmatch(rf"Ms ({WORD}) ({WORD}) and Ms ({WORD}) ({WORD}); ({WORD}) ({WORD})", b)
    assert m[1] == m[3].upper() and m[2] == m[4].upper() and m[3] == m[5] and m[3] in surrogates.GIVEN["f", "Latin"]
    m = re.fullmatch(rf"Mr ({WORD}) van der ({WORD}), ({WORD}) van der ({WORD})", c)
    assert m[1] == m[3] and m[2] == m[4] and "Berg" not in c
    assert d == "John Smith is not announced here"


def test_scripts_and_long_entities(spark):
    long = "A" + "b" * 60
    out = [r.text for r in rewritten(spark, [f"Mrs {long} called", "Mr Νίκος Παπαδόπουλος", "Mrs 王小明 came", "г-н Иван Петров; Иван Петров!", "l" * 70 + "@example.com", "x" * 300_000, None], extra=("found", "draws", "again", "n_distinct"))]
    assert "bbbb" not in out[0] and re.fullmatch(r"Mr [Ͱ-Ͽἀ-῿]+ [Ͱ-Ͽἀ-῿]+", out[1]) and "Παπαδόπουλος" not in out[1]
    assert re.fullmatch(r"Mrs [一-鿿]{3} came", out[2]) and "王小明" not in out[2]
    m = re.fullmatch(r"г-н ([А-Яа-яё]+ [А-Яа-яё]+); ([А-Яа-яё]+ [А-Яа-яё]+)!", out[3])
    assert m[1] == m[2] != "Иван Петров"
    assert re.fullmatch(r"[a-z]{70}@[a-z]{7}\.com", out[4]) and "llll" not in out[4] and out[5] == "x" * 300_000 and out[6] is None
    assert rewritten(spark, []) == []


def test_accounts_have_right_check_digits(spark):
    (row,) = rewritten(spark, ["DE89 3704 0044 0532 0130 00 and GB82WEST12345698765432"])
    for shape, iban in ((r"DE\d\d \d{4} \d{4} \d{4} \d{4} \d\d", row.text.split(" and ")[0]), (r"GB\d\d[A-Z]{4}\d{14}", row.text.split(" and ")[1])):
        assert re.fullmatch(shape, iban)
        plain = iban.replace(" ", "")
        assert int("".join(str(int(c, 36)) for c in plain[4:] + plain[:4])) % 97 == 1


@pytest.mark.parametrize("inline", [500, 0])
def test_all_entities_of_a_table_one_to_one(spark, monkeypatch, inline):
    monkeypatch.setattr(surrogates, "INLINE", inline)
    r = random.Random(5)
    people = [f"{r.choice(['Mr', 'Mrs', 'Dr'])} {a}{b} {c}{d}" for a in ("An", "Be", "Cy", "Do") for b in ("a", "o", "us") for c in ("Kor", "Lim", "Nap", "Os") for d in ("sen", "ter", "ov")]
    mails = [f"{c}{k}@{h}.io" for c in "abcdefgh" for k in ("", "1", "2") for h in ("a", "b")]
    numbers = [f"555-{k:03d}-{k * 7 % 10000:04d}" for k in range(60)]
    every = people + mails + numbers
    out = rewritten(spark, every)
    new = [x.text for x in out]
    assert len(set(new)) == len(set(every)) and not set(new) & set(every) and all(x.n_entities == 1 for x in out)
    surname, given = {}, {}
    for old, now in zip(people, new, strict=False):
        assert surname.setdefault(old.split()[2], now.split()[2]) == now.split()[2]
        key = old.split()[:2]
        assert given.setdefault(tuple(key), now.split()[1]) == now.split()[1]
    assert len(set(surname.values())) == len(surname) and not set(surname.values()) & set(surname)


def test_more_names_than_short_surrogates_behind_a_title(spark, monkeypatch):
    """Two syllables make 16 surnames of four and few given names; 60 names need longer ones."""
    monkeypatch.setattr(surrogates, "SYLLABLES", {s: v[:2] for s, v in surrogates.SYLLABLES.items()})
    names = [f"Mr X{a}{b}" for a in "abcdefghij" for b in "klm"] + [f"Frau {g} Weber" for g in ("A" + c for c in "abcdefghijklmnopqrstuvwxyzäöüß")]
    made = [r.text for r in rewritten(spark, names, "k")]
    assert len(set(made)) == len(names) and not set(made) & set(names)
    assert all(s.split()[0] == n.split()[0] and len(s.split()) == len(n.split()) for s, n in zip(made, names, strict=True))
