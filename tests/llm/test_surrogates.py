"""Operator 4: types, formats, one-to-one maps, coreference."""

import re

from saferoads.llm.surrogates import MALE, Permutation, collisions, iban_check, luhn, network, replace_entities, surrogate

KEY = b"k"


def test_permutation_is_one_to_one_and_moves_everything():
    for n in (2, 3, 10, 97, 1000):
        p = Permutation(KEY, "t", n)
        image = [p(i) for i in range(n)]
        assert sorted(image) == list(range(n)) and all(i != x for i, x in enumerate(image))


def test_formats():
    s = lambda k, t, g="n": surrogate(KEY, k, t, g)
    assert re.fullmatch(r"[a-z]{4}\.\d\d@[a-z]{4}\d\.[a-z]{7}\.com", s("email", "that.92@mail2.example.com"))
    assert re.fullmatch(r"\+1 \(\d{3}\) \d{3}-\d{4}", s("phone", "+1 (743) 555-3824")) and s("phone", "+1 (743) 555-3824") != "+1 (743) 555-3824"
    card = s("card", "4111 1111 1111 1111")
    assert re.fullmatch(r"4\d{3} \d{4} \d{4} \d{4}", card) and luhn(card.replace(" ", ""))
    assert not luhn(s("card", "2123465659789241")) or luhn("2123465659789241")
    assert network(s("ip", "192.168.3.4")) == 3 and network(s("ip", "8.8.4.4")) == 0
    assert s("ip", "1.2.3.400") is None and s("iban", "DE00123456781234567890") is None
    good = "DE" + iban_check("DE", "370400440532013000") + "370400440532013000"
    new = s("iban", good)
    assert new != good and iban_check(new[:2], new[4:]) == new[2:4]
    assert re.fullmatch(r"[0-9a-f]{40}", s("secret", "2321bac4d15ec8f90433955bf9d3cf61da5bdd1e"))
    first = s("name", "Karl Weber", "m").split()[0].lower()
    assert first in MALE and first != "karl"
    assert s("name", "WEBER", "m").isupper() and re.fullmatch(r"[А-Я][а-я]+", s("name", "Иванов", "m"))


def test_small_sets_keep_entities_apart():
    for kind, texts in {"card": [f"4{i:012d}" for i in range(300)], "ip": [f"10.0.0.{i}" for i in range(256)], "email": [f"{a}{b}@x.org" for a in "abcde" for b in "fgh"], "name": [x.capitalize() for x in MALE]}.items():
        assert len({surrogate(KEY, kind, t, "m") for t in texts}) == len(texts)


def test_rows(spark):
    mail = "write to Ann.Lee7@mail2.example.com or ann.lee7@mail2.example.com!!"
    df = spark.createDataFrame(
        [(1, mail), (2, "ip 10.1.2.3### and again 10.1.2.3"), (3, None), (4, ""), (5, "nothing here"), (6, 'token = "2321bac4d15ec8f90433955bf9d3cf61da5bdd1e"'), (1, mail), (7, "Frau Anna Weber met Frau Weber, year 2024, 3.14")],
        "doc_id bigint, text string",
    )
    got = replace_entities(df, "k").collect()
    by = {r["doc_id"]: r for r in got}
    assert len(got) == 8 and by[3]["text"] is None and by[4]["text"] == "" and by[5]["text"] == "nothing here"
    a, b = re.findall(r"\S+@\S+\.com", by[1]["text"])
    assert a.lower() == b and a[0].isupper() and "lee7" not in b
    x, y = re.findall(r"10\.\d+\.\d+\.\d+", by[2]["text"])
    assert x == y != "10.1.2.3" and by[2]["n_entities"] == 2
    assert by[6]["kinds"] == ["secret"] and by[6]["text"].startswith('token = "') and "2321bac4" not in by[6]["text"]
    assert by[7]["n_entities"] == 2 and "2024, 3.14" in by[7]["text"]
    assert collisions(df, "k").count() == 0
    assert replace_entities(df.limit(0), "k").count() == 0


def test_columns_stay(spark):
    df = spark.createDataFrame([(1, "a@b.org", "en", "kinds", 7)], "doc_id bigint, text string, lang string, kinds string, n_chars bigint")
    r = replace_entities(df, "k", keep_columns=True).first()
    assert r["kinds"] == "kinds" and r["text"] != "a@b.org" and r["n_chars"] == len(r["text"])


def test_names_agree_throughout_a_text(spark):
    text = "Frau Julia Weber wrote. Dr Weber replied to Mr Paul Young; Frau Weber and Julia left, Weber said. Herr Weber's son Paul, PROF WEBER."
    new = replace_entities(spark.createDataFrame([(1, text)], "doc_id bigint, text string"), "k").first()
    out = new["text"]
    given, family = re.match(r"Frau (\w+) (\w+) wrote", out).groups()
    from saferoads.llm.surrogates import FAMILY, FEMALE

    assert given.lower() in FEMALE and family.lower() in FAMILY and (given, family) != ("Julia", "Weber")
    assert re.findall(r"(?:Dr|Frau|Herr|,) (\w+)(?= replied| and|'s| said)", out) == [family] * 4 and f"and {given} left" in out and f"PROF {family.upper()}" in out
    assert not {"Julia", "Weber", "WEBER", "Paul", "Young"} & set(re.findall(r"\w+", out)) - {given, family} and new["one_to_one"]


def test_names_of_other_scripts_and_without_a_title(spark):
    texts = ["Mr 王小明 called", "Herr Ιωάννης and Ms Ольга", "Mr محمد spoke", "Dr יוסף came", "we met Julia Kerstens there. Kerstens left", "no names at all, Then or Now"]
    got = [r["text"] for r in replace_entities(spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string"), "k").orderBy("doc_id").collect()]
    assert all(a != b for a, b in zip(got[:5], texts)) and got[5] == texts[5]
    assert re.fullmatch(r"Mr [\u4e00-\u9fff]{3} called", got[0]) and re.fullmatch(r"Mr [\u0600-\u06ff]+ spoke", got[2]) and re.fullmatch(r"Dr [\u0590-\u05ff]+ came", got[3])
    first, again = re.fullmatch(r"we met [A-Z]\w+ (\w+) there\. (\w+) left", got[4]).groups()
    assert first == again != "Kerstens"


def test_all_listed_names_with_titles_are_one_to_one(spark):
    from saferoads.llm.surrogates import FAMILY, FEMALE

    rows = [(i, f"{t} {x.capitalize()}") for i, (t, x) in enumerate((t, x) for t in ("Mr", "Frau", "Dr") for x in MALE + FEMALE + FAMILY + ["kim", "tam", "bal"])]
    rows += [(1000 + i, f"Dr {g.capitalize()} {f.capitalize()}") for i, (g, f) in enumerate((g, f) for g in MALE[:5] + FEMALE[:5] for f in FAMILY)]
    assert collisions(spark.createDataFrame(rows, "doc_id bigint, text string"), "k").count() == 0


def test_birth_dates_and_long_addresses():
    s = lambda k, t: surrogate(KEY, k, t)
    assert re.fullmatch(r"\d{4}-\d\d-\d\d", s("birth", "1984-02-29")) and re.fullmatch(r"\d\d\.\d\d\.\d{4}", s("birth", "31.12.1999"))
    assert s("birth", "31.02.1999") is None and s("birth", "2500-01-01") is None
    assert len({s("birth", f"1990-01-{d:02d}") for d in range(1, 32)}) == 31
    import ipaddress

    for t in ("2001:db8::8a2e:370:7334", "fe80::1", "2001:DB8:0:0:8:800:200C:417A"):
        new = s("ip6", t)
        assert new != t and ipaddress.IPv6Address(new) and new.split(":")[0] == t.split(":")[0] and len(new) == len(t)
    assert s("ip6", "12:30:45") is None and s("ip6", "::") is None


def test_places_of_long_addresses_and_births(spark):
    text = "at 12:30:45 host fe80::1 born on 1984-02-29, seen 1984-02-29"
    r = replace_entities(spark.createDataFrame([(1, text)], "doc_id bigint, text string"), "k").first()
    assert r["kinds"] == ["birth", "ip6"] and "12:30:45" in r["text"] and r["text"].endswith("seen 1984-02-29")
