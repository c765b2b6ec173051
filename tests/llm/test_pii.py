"""Surrogates against a slow version in plain Python, on given texts and on tables with every form planted."""

import datetime
import re
from collections import Counter, defaultdict
from hashlib import sha256

import pytest
import regex

from cardsketch.llm import pii

ANY, NAME = regex.compile(pii.ANY), regex.compile(pii.NAME)
SCHEMA = "doc_id long, text string"


def digest(*parts):
    return sha256("|".join(map(str, parts)).encode()).hexdigest()


def slow_permuted(s, tweak, classes=pii.CLASSES):
    alpha = [next((a for a in classes if c in a), "") for c in s]
    v, m = [a.index(c) if a else 0 for a, c in zip(alpha, s)], len(s) // 2
    for k in range(pii.ROUNDS):
        own, other = (range(m), v[m:]) if k % 2 == 0 else (range(m, len(s)), v[:m])
        h = digest(tweak, k, ",".join(map(str, other)))
        for i, p in enumerate(own):
            v[p] = (v[p] + int(h[i % 32 * 2:i % 32 * 2 + 2], 16)) % max(1, len(alpha[p]))
    return "".join(a[x] if a else c for a, x, c in zip(alpha, v, s))


def luhn(s):
    d = [int(c) for c in s if c.isdigit()][::-1]
    return sum(x * 2 // 10 + x * 2 % 10 if i % 2 == 0 else x for i, x in enumerate(d)) % 10


def mod97(account):
    a = account.replace(" ", "")
    return int("".join(str(int(c, 36)) for c in a[4:] + a[:4])) % 97


def slow_kind(e):
    if "@" in e:
        return "email"
    for k in ("iban", "ipv6", "ip", "card", "phone", "ssn"):
        if regex.fullmatch(pii.FORMS[k], e):
            return "none" if k == "iban" and mod97(e) != 1 else k
    if re.fullmatch(r"\d{4}-\d\d-\d\d|\d\d[./]\d\d[./]\d{4}", e):
        return "birth"
    return "address" if re.search("[0-9]", e) else "name"


def extra(w, attempt):
    n = max(0, attempt - 1) if attempt < pii.FULL else 0
    return w + ("на" if regex.search(r"\p{IsCyrillic}$", w) else "na") * n


def slow_birth(e, tweak):
    forms = ["%Y-%m-%d"] if e[4] == "-" else ["%d.%m.%Y"] if "." in e else ["%m/%d/%Y"] if int(e[3:5]) > 12 else ["%d/%m/%Y"]
    base = datetime.date.fromisoformat(pii.FIRST_DAY)
    try:
        day = (datetime.datetime.strptime(e, forms[0]).date() - base).days
    except ValueError:
        day = -1
    if not 0 <= day < pii.DAYS:
        return slow_permuted(e, tweak)
    a, b = divmod(day, 271)
    for k in range(pii.ROUNDS):
        if k % 2 == 0:
            a = (a + int(digest(tweak, "birth", k, b)[:4], 16)) % 270
        else:
            b = (b + int(digest(tweak, "birth", k, a)[:4], 16)) % 271
    return (base + datetime.timedelta(a * 271 + b)).strftime(forms[0])


def slow_surrogate(e, attempt, key=pii.KEY):
    kind = slow_kind(e)
    tweak = f"{key}|{kind}|{attempt}"
    if kind == "none":
        return e
    if kind == "email":
        tail = re.search(r"((?:\.example)?\.[A-Za-z]+)$", e)[1]
        local, domain = e.split("@", 1)
        return slow_permuted(extra(local, attempt) + "@" + domain[:len(domain) - len(tail)], tweak) + tail
    if kind == "ip":
        o = [int(x) for x in e.split(".")]
        a, b = o[0] * 256 + o[1], o[2] * 256 + o[3]
        for k in range(pii.ROUNDS):
            a, b = b, a ^ int(digest(tweak, "ip", k, b)[:4], 16)
        return ".".join(map(str, (a // 256, a % 256, b // 256, b % 256)))
    if kind == "card":
        head = slow_permuted(e[:-1], tweak)
        return head + str((int(e[-1]) + luhn(e[:-1]) - luhn(head)) % 10)
    if kind == "iban":
        body = slow_permuted(e[4:], tweak)
        return f"{e[:2]}{98 - mod97(e[:2] + '00' + body):02d}{body}"
    if kind == "ipv6":
        return slow_permuted(e, tweak, pii.HEX_CLASSES)
    if kind == "birth":
        return slow_birth(e, tweak)
    if kind == "name":
        words = e.split(" ")
        out = []
        for i, w in enumerate(words):
            names = next((x for x in pii.LISTS if w in x), None)
            if i == 0 and len(words) > 1 and names:
                out.append(pii.cycle(names, key, attempt % pii.ATTEMPTS)[w])
            else:
                out.append(slow_permuted(extra(w, attempt) if i == len(words) - 1 else w, tweak))
        return " ".join(out)
    if kind == "address":
        out = []
        for w in e.split(" "):
            if re.sub(",$", "", w) in pii.STREETS:
                out.append(w)
                continue
            tail = (re.search(f"(?:{'|'.join(pii.STREET_ENDS)})$", w) or [""])[0]
            stem = w[:len(w) - len(tail)]
            out.append(slow_permuted(extra(stem, attempt) if regex.match(r"\p{Lu}", stem) else stem, tweak) + tail)
        return " ".join(out)
    head = re.match(r"(?:\+\d{1,3})?", e)[0]
    return head + slow_permuted(e[len(head):], tweak)


def canonical(e):
    return regex.sub(rf"^(?:{'|'.join(pii.HONORIFICS)})\.? (?=\p{{Lu}})", "", e)


def slow_replace(rows, moved):
    out = []
    for i, t in rows:
        if t is None:
            out.append((i, None, 0))
            continue
        pattern, n = (ANY if re.search("[0-9@]", t) else NAME), 0

        def one(m):
            nonlocal n
            c = canonical(m[0])
            n += slow_kind(c) != "none"
            return m[0][:len(m[0]) - len(c)] + slow_surrogate(c, moved.get(c, 0))

        out.append((i, pattern.sub(one, t), n))
    return out


PLANTED = {
    "email": ["jo.smith+x@mail3.example.com", "bob@corp-x.org", "é.b@a-b.co.uk"], "iban": ["DE89 3704 0044 0532 0130 00", "GB82WEST12345698765432"], "ipv6": ["2001:db8::1", "fe80:0:0:0:1:2:3:4"], "ip": ["10.200.0.7"],
    "card": ["4111111111111111", "5500 0000 0000 0004", "4111-1111-1111-1111"], "phone": ["+49 170 1234567", "+33 6 12 34 56 78", "+49 30 12345678", "+1 (017) 555-7713", "555.123.4567", "06 12 34 56 78", "030 12345678"], "ssn": ["123-45-6789"],
    "birth": ["born 1980-02-03", "geboren am 03.02.1980", "née le 13/02/1980", "DOB: 02/13/1980"], "address": ["12 Main St", "221b Baker Street", "Hauptstraße 5a", "12 rue de la Paix", "Calle de Alcalá 42"],
    "name": ["Jane Doe", "Maria Lopez", "Wei Zhang", "Mr. James Miller", "Frau Müller", "Анна Петрова", "Dr. Xu Li", "my name is Quentin Zork"],
}


def planted(n=3):
    return [(i, f"before {e} and again {e}, after") for i, e in enumerate(e for es in PLANTED.values() for e in es * n)]


def moved_of(x):
    return {r["entity"]: r["attempt"] for r in pii.clashes(x).collect()}


@pytest.mark.parametrize("name", ["planted", "given"])
def test_slow_version(spark, sf_dir, name):
    rows = planted() if name == "planted" else [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()]
    rows += [(90_001, None), (90_002, ""), (90_003, "nothing here. Really 12 or 3.5 or 2019-02-03, at 12:30"), (90_004, "DE88 3704 0044 0532 0130 00")]
    x = spark.createDataFrame(rows, SCHEMA)
    got = [(r["doc_id"], r["text"], r["n_entities"]) for r in pii.replace(x).collect()]
    want = sorted(slow_replace(rows, moved_of(x)), key=str)
    assert sorted(got, key=str) == want
    assert {t for i, t, _ in got if i in (90_003, 90_004)} == {rows[-2][1], rows[-1][1]}


def test_every_form_is_found(spark):
    rows = planted(1)
    out = {r["doc_id"]: r for r in pii.replace(spark.createDataFrame(rows, SCHEMA)).collect()}
    kinds = [k for k, es in PLANTED.items() for _ in es]
    for (i, t), kind in zip(rows, kinds):
        r = out[i]
        assert r[f"n_{kind}"] == 2 and r["n_entities"] == 2 and r["text"] != t, (kind, t, r)
        a, b = re.fullmatch(r"before (.+) and again (.+), after", r["text"]).groups()
        assert a == b
    new = {e: re.fullmatch(r"before (.+) and again .+, after", out[i]["text"])[1] for i, e in enumerate(e for es in PLANTED.values() for e in es)}
    assert mod97(new["DE89 3704 0044 0532 0130 00"]) == 1 and luhn(new["4111111111111111"] + "0") == 0
    assert new["born 1980-02-03"].startswith("born ") and datetime.date.fromisoformat(new["born 1980-02-03"][5:])
    assert new["Hauptstraße 5a"].split(" ")[0].endswith("straße") and new["12 Main St"].endswith(" St")
    assert new["Jane Doe"].split()[0] in pii.FEMALE and new["Mr. James Miller"].startswith("Mr. ") and new["Анна Петрова"].split()[0] in pii.FEMALE_CYRILLIC


@pytest.mark.parametrize("names", [
    ["Mary Patricia", "Patricia Jennifer", "Jennifer Mary"],
    [f"Mr. {a}{b}" for a in "AEIOU" for b in "aeiou"],
    [f"Mr. {a}{b}" for a in "AEIOU" for b in "aeiou"][:14],
    [f"James {a}{b}" for a in "AEIOU" for b in "aeiou"],
])
def test_full_shapes(spark, names):
    """Listed names after each other, and shapes all or over half of whose strings occur: no error, one to one, no original."""
    x = spark.createDataFrame(list(enumerate(names)), SCHEMA)
    got = [r["text"] for r in pii.replace(x).collect()]
    assert len(set(got)) == len(names) and not set(got) & set(names)


def test_full_digit_shapes_are_permuted(spark):
    """Numbers can't grow: where no tweak does, all of the shape take one permutation."""
    x = spark.createDataFrame([(i, f"see 10.0.0.{i}") for i in range(4)], SCHEMA)
    full = {"10.0.0.0": pii.FULL, "10.0.0.1": pii.FULL}
    assert len({slow_surrogate(e, a) for e, a in full.items()}) == 2
    assert len({r["text"] for r in pii.replace(x).collect()}) == 4


def test_long_texts_of_every_form(spark):
    n = 300_000
    long = ["x@" + "a." * 5000 + "com", "x@" + "a." * n + "com", "a" * n + "@example.com", "1" * n, "1 " * n, "+" + "1 22" * n, "Mr. " + "A" * n, "A " * n, "2001:" * n, "1." * n, "DE89" + "ABCD" * n, "Aa " * n, "-" * n, "(123) " * n, "12 " + "Aa " * n]
    rows = pii.replace(spark.createDataFrame([(i, f"{t} mail bob@corp.org") for i, t in enumerate(long)], SCHEMA)).collect()
    assert len(rows) == len(long) and all("bob@corp.org" not in r["text"] for r in rows)


def test_another_key_gives_other_surrogates(spark):
    x = spark.createDataFrame(planted(1), SCHEMA)
    seen = defaultdict(set)
    for key in ("a", "b", "c", "ab", "ba"):
        for r in pii.replace(x, key=key).collect():
            seen[r["doc_id"]].add(r["text"])
    assert Counter(len(v) for v in seen.values())[5] >= len(seen) - 4 and min(len(v) for v in seen.values()) >= 4
