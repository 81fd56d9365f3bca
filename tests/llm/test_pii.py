import hashlib
import random
import re

import pytest

from tiersort.llm import pii
from tiersort.llm.queries import QUERIES
from helpers import DATA


def plain(text):
    """Straight reading of the base rules."""
    out = {"email": [m.span() for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)],
           "ip": [m.span() for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(p) <= 255 for p in m[0].split("."))], "card": [], "phone": []}
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
        d = [int(c) for c in m[0] if c.isdigit()]
        if 13 <= len(d) <= 19 and sum(x if i % 2 == 0 else sum(divmod(2 * x, 10)) for i, x in enumerate(d[::-1])) % 10 == 0:
            out["card"].append(m.span())
    for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text):
        if 9 <= len(re.sub(r"[^0-9]", "", m[0])) <= 15:
            out["phone"].append(m.span())
    return out


def test_base_on_random_text():
    rng = random.Random(8)
    for _ in range(4000):
        t = "".join(rng.choice("ab@@..-+ 0123456789()%é") for _ in range(rng.randrange(80)))
        assert pii.detect(t) == plain(t), t


def test_base_on_given_documents(spark):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{DATA}/documents.parquet").select("doc_id", "text").collect()}
    for r in QUERIES["op6_pii"](spark, DATA).collect():
        want = plain(docs[r.doc_id])
        flat = [f"{k}:{a}:{b}" for k in pii.KINDS for a, b in want[k]]
        assert r.base_sha256 == hashlib.sha256(",".join(flat).encode()).hexdigest()
        assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == tuple(len(want[k]) for k in pii.KINDS)
        assert set(flat) <= set(r.spans.split(",")) | {""}


@pytest.mark.parametrize("text, kind, part", [
    ("write to jane.doe [at] mail (dot) example [dot] org now", "email", "jane.doe [at] mail (dot) example [dot] org"),
    ("write to jane at example dot org today", "email", "jane at example dot org"),
    ("ask jаne@exаmple.org please", "email", "jаne@exаmple.org"),  # Cyrillic a
    ("mail ｊｏｅ＠example．com!", "email", "ｊｏｅ＠example．com"),
    ("host １０.0.0.７ is up", "ip", "１０.0.0.７"),
    ("call plus +four nine one five one two three four five six seven", "phone", "+four nine one five one two three four five six seven"),
    ("card four one one one one one one one one one one one one one one one end", "card", "four one one one one one one one one one one one one one one one"),
])
def test_disguises(text, kind, part):
    base = pii.detect(text)
    got = pii.disguised(text, base)
    assert [text[a:b] for a, b in got[kind]] == [part]
    assert part not in pii.mask(text)


def test_plain_prose_is_left_alone():
    for text in ("we met at noon and a dot was seen", "one two three go", "look at the point, it is at home", "null und nichts"):
        assert pii.listed(pii.disguised(text, pii.detect(text))) == ""


def test_base_spans_stay():
    text = "a@b.co and c [at] d.org, +49 170 1234567 at 10.0.0.1"
    base = pii.detect(text)
    extra = pii.disguised(text, base)
    assert pii.listed(base) == "email:0:6,ip:44:52,phone:25:40"
    assert [text[a:b] for a, b in extra["email"]] == ["c [at] d.org"]


def test_edge_rows(spark):
    rows = [(1, None, "x"), (2, "", None), (3, "a@b.c " * 20000, "y"), (3, "a@b.c", "y"), (None, "1" * 5000, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string, spans string")
    got = sorted((r.id or 0, r.n_email) for r in pii.personal_data(df).collect())
    assert got == [(0, 0), (1, 0), (2, 0), (3, 1), (3, 20000)]
    assert pii.personal_data(df.limit(0)).count() == 0


@pytest.mark.parametrize("text, kind, part", [
    ("call +1 555 123 four five now", "phone", "+1 555 123 four five"),
    ("card 4111 1111 1111 11 one one end", "card", "4111 1111 1111 11 one one"),
    ("nom arobase exemple point fr", "email", "nom arobase exemple point fr"),
])
def test_short_disguises_wake_the_transducer(text, kind, part):
    got = pii.disguised(text, pii.detect(text))
    assert [text[a:b] for a, b in got[kind]] == [part]


def test_planted_disguises_are_found():
    """Random identifiers in random disguises: what is found is the disguised stretch itself."""
    rng = random.Random(12)
    names = {"0": "zero", "1": "one", "2": "two", "3": "three", "4": "four", "5": "five", "6": "six", "7": "seven", "8": "eight", "9": "nine"}
    alike = {"a": "а", "e": "е", "o": "о", "c": "с", "p": "р", "x": "х"}
    word = lambda n: "".join(rng.choice("bdfghklmnrstv") + rng.choice("aeo") for _ in range(n))
    wide = lambda t: "".join(chr(ord(c) + 0xFEE0) if c.isdigit() and rng.random() < 0.7 else c for c in t)
    for _ in range(400):
        kind = rng.choice(["email", "ip", "card", "phone"])
        if kind == "email":
            at, dot = rng.choice([(" [at] ", " [dot] "), ("(at)", "(dot)"), (" at ", " dot "), ("＠", "．"), ("@", ".")])
            hidden = word(2) + at + word(3) + dot + rng.choice(["org", "net", "example"])
            if at == "@":
                k = next(i for i, c in enumerate(hidden) if c in alike and i > hidden.index("@"))  # what stands before it may be a base match
                hidden = hidden[:k] + alike[hidden[k]] + hidden[k + 1:]
        elif kind == "ip":
            hidden = wide(".".join(str(rng.randrange(256)) for _ in range(4)))
            if hidden.isascii():
                hidden = chr(ord(hidden[0]) + 0xFEE0) + hidden[1:]
        elif kind == "card":
            digits = [rng.randrange(10) for _ in range(15)]
            check = next(x for x in range(10) if pii.luhn("".join(map(str, [*digits, x]))))
            hidden = " ".join(names[str(x)] for x in [*digits, check])
        else:
            hidden = "+" + " ".join(names[str(rng.randrange(1, 10))] for _ in range(rng.randrange(9, 14)))
        text = f"please note: {hidden} ; thanks, {word(3)}"
        found = pii.disguised(text, pii.detect(text))[kind]
        assert [text[a:b] for a, b in found] == [hidden], (kind, text, found)
