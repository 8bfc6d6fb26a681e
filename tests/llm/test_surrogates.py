"""Surrogates: what is found, that types, formats and coreference hold, that nothing collides, and the text put together again."""

import itertools
import random
import re

import pytest
from cellstream.llm import surrogates
from pyspark.sql import functions as F

KEY = b"k"
PII = (
    "Mail The.99@mail3.example.com or the.99@mail3.example.com, call +1 (555) 123-4567, ip 10.1.2.3 and 8.8.4.4. Card 4111111111111111, 4111 1111 1111 1111, 1234567812345678. "
    "Mr. James Smith met Ms. Mary Jones; Mr Smith left, Mary and James Smith too. token = \"9fdf9a99c9b9d999c9b9c9d999eda9ac99d999d9\" SSN 123-45-6789 "
    "IBAN DE89370400440532013000 alias DE89 3704 0044 0532 0130 00."
)


def swap(text, key=KEY):
    return surrogates.replaced(text, key, {})[0]


def test_letters_only_secret_in_a_text_without_digits(spark):
    texts = ["password: correcthorsebatterystaple", "my API_KEY = 'abcdefghijklmnop' here", "Secret=QWERTYUIOPASDF", "the token: short"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    out = {r["doc_id"]: r for r in surrogates.pseudonymised(df, b"k", count="n").collect()}
    assert [out[d]["n"] for d in range(4)] == [1, 1, 1, 0] and out[3]["text"] == texts[3]
    for d, secret in enumerate(["correcthorsebatterystaple", "abcdefghijklmnop", "QWERTYUIOPASDF"]):
        assert secret not in out[d]["text"] and len(out[d]["text"]) == len(texts[d])


def test_one_person_has_one_name():
    new = swap("Mr John Smith met Mr Smith. John Smith left. A Smith, and John; no Johnson, no smith.")
    a, b = re.match(r"Mr (\w+) (\w+) met", new).groups()
    assert new == f"Mr {a} {b} met Mr {b}. {a} {b} left. A {b}, and {a}; no Johnson, no smith." and a in surrogates.NAMES["m"] and "Smith" not in new
    assert swap("Dr. Jane Doe").split()[1] in surrogates.NAMES["f"] and swap("Frau Yvette Doe").split()[1].endswith("ella") and swap("Mr Mustafa Doe").split()[1].endswith("andro")


@pytest.mark.parametrize("name", ["王小明", "Müller", "Łukasz", "Ελένη", "Иванов", "محمد", "אברהם", "김철수", "Ñandú", "O'Neil", "Jean-Luc"])
def test_names_of_any_script_change_and_keep_script_and_case(name):
    new = swap(f"Mr {name} and again {name}.")
    found = new[3 : 3 + len(name)]
    assert new == f"Mr {found} and again {found}." and name not in new
    for x, y in zip(name, found, strict=True):
        assert x.isalpha() == y.isalpha() and x.isupper() == y.isupper() and surrogates._script(x) == surrogates._script(y)


def test_formats_and_check_digits():
    new = swap(PII)
    iban = re.search(r"IBAN (\w+) alias ([\w ]+)\.", new).groups()
    assert iban[1].replace(" ", "") == iban[0] and int("".join(str(int(c, 36)) for c in iban[0][4:] + iban[0][:4])) % 97 == 1 and iban[0][:2] == "DE"
    cards = re.search(r"Card (\d+), ([\d ]+), (\d+)\.", new).groups()
    assert cards[1].replace(" ", "") == cards[0] and surrogates._luhn(cards[0]) and cards[0][0] == "4" and surrogates._luhn(cards[2]) == surrogates._luhn("1234567812345678")
    assert re.search(r"call \+1 \(\d{3}\) \d{3}-\d{4}, ip (10|172|192)\.[\d.]+ and ", new)
    mails = re.findall(r"\S+@\S+\.example\.com", new)
    assert mails[0].lower() == mails[1] and mails[0][0].isupper()
    assert "+49" in swap("dial +49 30 1234567 now") and swap("+49 30 1234567") != "+49 30 1234567"


def test_moves_are_one_cycle():
    for size in (2, 3, 10, 97, 1000):
        assert sorted(surrogates.permuted(v, size, b"k", b"t") for v in range(size)) == list(range(size))
        at, seen = 0, 0
        while at or not seen:
            assert surrogates.permuted(surrogates.permuted(at, size, b"k", b"t"), size, b"k", b"t", back=True) == at
            at, seen = surrogates.moved(at, size, b"k", b"t"), seen + 1
        assert seen == size


def test_small_domains_by_brute_force():
    """Every value of small formats: a one-to-one map that leaves none where it was."""
    domains = {
        "given": ["".join(x) for x in itertools.product("abei", repeat=3)], "family": ["".join(x).capitalize() for x in itertools.product("xyzéè", repeat=3)],
        "card": [f"4{k:03d}00000000{c}" for k in range(40) for c in range(10)], "ip": [f"{a}.{b}.0.1" for a in (10, 127, 172, 192, 8, 224) for b in range(0, 256, 9)],
        "iban": [f"XK{c:02d}{k:012d}" for k in range(12) for c in range(100)], "ssn": [f"{a:03d}-{b:02d}-0001" for a in range(0, 1000, 37) for b in range(0, 100, 9)],
    }
    for kind, values in domains.items():
        out = {v: surrogates.surrogate(kind, v, KEY) for v in values}
        assert len(set(out.values())) == len(values) and all(v != s for v, s in out.items()), kind
    genders = {surrogates.surrogate("given", n, KEY, g) for g in "mfn" for n in [*domains["given"], *itertools.chain(*surrogates.NAMES.values())]}
    assert len(genders) == 3 * 64 + 44


def test_against_entities_put_in_by_hand(spark, docs, rows):
    """Known entities between words: each is found whole, every spelling of one has one surrogate, and all else stays."""
    rng = random.Random(5)
    pool = ["john.{}@mail.example.com", "+1 (555) 1{:02d}-4567", "8.8.{}.4", "4111 1111 1111 {:04d}", "{:03d}-45-6789", "DE89 3704 0044 0532 0130 {:02d}", "token = \"c0ffee{:010d}abcdef0123\"", "Mr Stone{}", "Frau Ada Ölmann"]
    texts, put = {}, {}
    for d in range(60):
        parts, inside = [], []
        for _ in range(rng.randint(0, 9)):
            form = rng.choice(pool)
            entity = re.sub(r"\{.*?\}", lambda m: m.group().format(rng.randint(1, 40)), form)
            entity = entity.translate(str.maketrans("0123456789", "abcdefghij")) if entity.startswith("Mr") else entity
            inside.append(entity)
            parts += [rng.choice(["some words", "more of it", "a b c", ""]), entity, ";"]
        texts[d], put[d] = " ".join(parts), inside
    texts |= {60: None, 61: "", 62: PII, 63: "x" * 200_000 + " 8.8.8.8"}
    df = spark.createDataFrame([*texts.items(), (None, PII), (62, PII)], "doc_id long, text string").withColumn("noted", F.lit(1)).withColumn("start", F.lit("s"))
    got = surrogates.pseudonymised(df, KEY, count="n")
    assert got.columns == ["doc_id", "text", "noted", "start", "n"]
    new = {r["doc_id"]: r for r in got.collect() if r["doc_id"] is not None}
    assert got.count() == 66 and new[60]["text"] is None and new[61]["text"] == "" and new[60]["n"] == 0 and new[63]["n"] == 1
    table = surrogates.entity_table(df.where("doc_id is not null and doc_id <> 62"), KEY).collect()
    one, other = {}, {}
    for r in table:
        kind = "name" if r["kind"] in ("given", "family") else r["kind"]
        v, s = ((r["kind"], surrogates.identity(kind, r[k])) for k in ("value", "surrogate"))
        assert one.setdefault(v, s) == s and other.setdefault(s, v) == v and v != s
        assert texts[r["doc_id"]][r["start"] : r["end"]] == r["value"]
    for d, entities in put.items():
        spans = sorted((r["start"], r["end"], r["surrogate"]) for r in table if r["doc_id"] == d)
        built, at = "", 0
        for a, b, s in spans:
            built, at = built + texts[d][at:a] + s, b
        assert built + texts[d][at:] == new[d]["text"] and len(spans) == new[d]["n"]
        held = {texts[d][a:b] for a, b, _ in spans}
        for e in entities:
            whole = [e.split('"')[1]] if e.startswith("token") else e.split(" ")[1:] if e.startswith(("Mr", "Frau")) else [e]
            assert set(whole) <= held, (e, held)
    assert surrogates.collisions(docs, KEY).count() == 0
    same = {r["doc_id"]: r["text"] for r in surrogates.pseudonymised(docs, KEY).collect()}
    for d, t in rows.items():
        if t is None or not list(surrogates.entities(t)):
            assert same[d] == t


def test_collisions_are_raised(spark, monkeypatch):
    monkeypatch.setattr(surrogates, "_colliding", lambda pairs: pairs)
    df = spark.createDataFrame([(1, PII)], "doc_id long, text string")
    with pytest.raises(surrogates.Collision):
        surrogates.pseudonymised(df, KEY)
    pairs = spark.createDataFrame([(1, 5), (2, 6), (1, 5), (3, 6), (4, 7), (4, 8)], "v long, s long")
    monkeypatch.undo()
    assert {(r["side"], r["digest"]) for r in surrogates._colliding(pairs).collect()} == {("s", 6), ("v", 4)}
