"""Surrogates of titled names and of formats with few values, on small fixtures."""

import itertools
import re
import string

from twigrank.llm import pii

KEY = "k"


def replaced(spark, texts):
    rows = pii.replace_pii(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), KEY).collect()
    return [r["text"] for r in sorted(rows, key=lambda r: r["doc_id"])]


def test_no_surrogate_name_is_a_real_one(spark):
    olds = ["Mr Smith", "Mrs Jones", "Herr Bauer", "Frau Anna Weber", "Господин Иванов"]
    reals = replaced(spark, olds)
    assert all(old != new and old.split()[0] == new.split()[0] for old, new in zip(olds, reals))
    new = replaced(spark, olds + reals)
    assert not set(new) & set(olds + reals) and len(set(new)) == len(new)


def test_full_formats_are_settled_exactly(spark):
    """2,100 short names where two syllables give 2,025, and the 26 addresses of one letter at one domain."""
    words = ["".join(w).capitalize() for w in itertools.islice(itertools.product(string.ascii_lowercase, repeat=3), 2100)]
    olds = [f"Mr {w}" for w in words] + [f"Mr {words[7]} {words[k]}" for k in range(40)] + [f"Mrs {words[k]} {words[9]}" for k in range(40)] + [f"{c}@example.com" for c in string.ascii_lowercase]
    news = replaced(spark, olds)
    assert len(set(news)) == len(olds) and not set(news) & set(olds)
    assert len({m[1] for m in map(re.compile(r"^[a-z]+@(\w{7}\.com)$").match, news[-26:])}) == 1
    family = dict(zip(words, (n.split()[1] for n in news[:2100])))
    assert [n.split()[-1] for n in news[2100:2140]] == [family[words[k]] for k in range(40)]
    assert {n.split()[-1] for n in news[2140:2180]} == {family[words[9]]}
    assert len({n.split()[1] for n in news[2100:2140]}) == 1 and all(n.split()[1].endswith("a") for n in news[2140:2180])
    assert not {w.lower() for w in family.values()} & {w.lower() for w in words}


def test_people_keep_one_surrogate_without_their_title(spark):
    olds = ["Mr. John Smith met Anna Lee. John Smith left; Smithson and Smith's dog stayed, smith too.", "Frau Weber sah Weber.", "Weber war nicht da."]
    news = replaced(spark, olds)
    name = re.match(r"Mr\. (\w+ \w+) met Anna Lee\. ", news[0])[1]
    family = name.split()[1]
    assert "Smith " not in news[0] and news[0] == f"Mr. {name} met Anna Lee. {name} left; Smithson and {family}'s dog stayed, smith too."
    weber = news[1].split()[1]
    assert weber != "Weber" and news[1] == f"Frau {weber} sah {weber}." and news[2] == olds[2]


def test_addresses_and_accounts_keep_their_form(spark):
    olds = ["from 2001:db8::1 and 2001:DB8::1 to fe80:0:0:0:1:2:3:4.", "DE89 3704 0044 0532 0130 00 or DE89370400440532013000", "GB12ABCD12345612345678", "at 12:30:45 in C::D std::cout", None]
    news = replaced(spark, olds)
    a, b, c = re.match(r"from (\S+) and (\S+) to (\S+)\.$", news[0]).groups()
    assert a != "2001:db8::1" and a.lower() == b.lower() and re.fullmatch(r"[0-9a-f]{4}:[0-9a-f]{3}::[0-9a-f]", a) and re.fullmatch(r"[0-9a-f]{4}(:[0-9a-f]){7}", c)
    x, y = news[1].split(" or ")
    assert x.replace(" ", "") == y != "DE89370400440532013000" and [len(p) for p in x.split()] == [4, 4, 4, 4, 4, 2]
    digits = "".join(str(int(ch, 36)) for ch in y[4:] + y[:4])
    assert y[:2] == "DE" and int(digits) % 97 == 1
    assert news[2][:4] == "GB12" and re.fullmatch(r"GB12[A-Z]{4}[0-9]{14}", news[2]) and news[2] != olds[2]
    assert news[3:] == olds[3:]


def test_formats_of_few_addresses_and_accounts_are_settled(spark):
    olds = [f"a1::{x}" for x in "0123456789abcdef"] + [f"DE{k:02d}1111222233334444" for k in range(40)]
    news = replaced(spark, olds)
    assert len(set(news)) == len(olds) and not set(news) & set(olds)
