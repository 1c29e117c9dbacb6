import random
import re

from pyspark.sql import functions as F

from ranksort.llm import pii

PLAIN = {
    "email": (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda m: True),
    "ip": (r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda m: all(int(x) <= 255 for x in m.split("."))),
    "card": (r"[0-9]([\x20-]?[0-9])+", lambda m: 16 <= len(digits(m)) <= 19 and luhn(digits(m))),
    "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: 8 <= len(digits(m)) <= 15),
}


def digits(text):
    return re.sub("[^0-9]", "", text)


def luhn(number):
    twice = [int(d) * (1 + i % 2) for i, d in enumerate(reversed(number))]
    return sum(d - 9 * (d > 9) for d in twice) % 10 == 0


def expected(text):
    return {k: [(m.start(), m.end()) for m in re.finditer(p, text) if ok(m[0])] for k, (p, ok) in PLAIN.items()}


def mod97(account):
    return int("".join(str(int(c, 36)) for c in account[4:] + account[:4])) % 97 == 1


def ibans(text):
    """From each place, as many units of a character with or without a blank before it as there are, 30 at most; no way back."""
    out, at = [], 0
    while m := re.compile("[A-Z]{2}[0-9]{2}").search(text, at):
        end, units = m.end(), 0
        while units < 30 and (u := re.compile(" ?[A-Z0-9]").match(text, end)):
            end, units = u.end(), units + 1
        bare = lambda c: c.isascii() and c.isalnum()
        if units >= 11 and not (m.start() and bare(text[m.start() - 1])) and not (end < len(text) and bare(text[end])):
            out.append((m.start(), end))
            at = end
        else:
            at = m.start() + 1
    return out


ADDED = {
    "iban": (ibans, lambda m: mod97(m.replace(" ", "")), 0.8, "iban account bank konto cuenta compte", ""),
    "local_phone": (r"(?<![0-9A-Za-z+.-])(?:\([0-9]{3}\) ?|[0-9]{3}[ .-])[0-9]{3}[ .-][0-9]{4}(?![0-9A-Za-z])", lambda m: True, 0.3, "phone tel call mobile fax whatsapp cell", "order invoice serial part"),
    "tax_id": (r"(?<![0-9A-Za-z-])(?!000|666|9)[0-9]{3}-(?!00)[0-9]{2}-(?!0000)[0-9]{4}(?![0-9A-Za-z-])", lambda m: True, 0.4, "ssn social security tax", "order invoice serial part"),
}


def added(text):
    """Spans of the added kinds whose score, by the words near by, is 0.7 or more."""
    out = {}
    for kind, (pattern, ok, prior, near, against) in ADDED.items():
        places = pattern(text) if callable(pattern) else [m.span() for m in re.finditer(pattern, text)]
        out[kind] = []
        for i, (a, b) in enumerate(places):
            before, after = text[places[i - 1][1] if i else 0 : a], text[b : places[i + 1][0] if i + 1 < len(places) else len(text)]
            words = re.findall(r"\b\w+", f"{before[-40:]} {after[:24]}".lower())
            said = lambda terms: any(w.startswith(t) for w in words for t in terms.split())
            if ok(text[a:b]) and prior + 0.4 * said(near) - 0.3 * bool(against and said(against)) >= 0.7 - 1e-9:
                out[kind].append((a, b))
    return out


def brute(text):
    """All spans: kind, start, end, by kind, then start."""
    return [(kind, a, b) for kind, places in (expected(text) | added(text)).items() for a, b in places]


def brute_redacted(text):
    out, at = [], 0
    for kind, a, b in sorted(brute(text), key=lambda x: (x[1], -x[2])):
        if a >= at:
            out += [text[at:a], f"<{kind.upper()}>"]
            at = b
    return "".join(out) + text[at:]


def test_all_kinds_against_brute_force(spark):
    rng = random.Random(2)
    parts = ["GB82 WEST 1234 5698 7654 32", "DE89370400440532013000", "GB82", "iban ", "account", "A1", " ", "x", "555-123-4567", "(555) 123-4567", "call ", "order ", "part", "123-45-6789", "ssn ", "900-45-6789", "tax", "a@b.cc", "+49 30 1234567", "10.0.0.1", ", ", "-", "\n"]
    texts = ["".join(rng.choice(parts) for _ in range(rng.randrange(1, 25))) for _ in range(500)]
    df = spark.createDataFrame(list(enumerate(texts)), "id long, text string")
    rows = pii.find_spans(df).withColumn("clean", pii.redact(F.col("text"), F.col("pii_spans"))).collect()
    for r in rows:
        assert [(s.kind, s.start, s.end) for s in r.pii_spans] == brute(r.text), r.text
        assert r.clean == brute_redacted(r.text)
    assert {k for t in texts for k, *_ in brute(t)} >= set(ADDED)


def found(spark, texts, **options):
    df = spark.createDataFrame(list(enumerate(texts)), "id long, text string")
    rows = pii.find_spans(df, **options).orderBy("id").collect()
    return [[(s.kind, s.start, s.end, s.score) for s in r.pii_spans] for r in rows]


def test_base_spans_against_plain_patterns(spark):
    rng = random.Random(1)
    parts = ["a", "B9", "@", "@x.y", ".", "-", "_", " ", "1", "255", "256", "10.0.0.1", "+49 30 1234567", "4111 1111 1111 1111", "4111111111111112", "é", "𝒳", "\n", "(", ")", "%"]
    texts = ["".join(rng.choice(parts) for _ in range(rng.randrange(1, 60))) for _ in range(400)]
    for text, spans in zip(texts, found(spark, texts)):
        for kind, places in expected(text).items():
            assert [(a, b) for k, a, b, _ in spans if k == kind] == places, text


def test_context_and_checksums(spark):
    texts = [
        "IBAN: GB82 WEST 1234 5698 7654 32 thanks", "IBAN GB82WEST12345698765433", "ref DE89370400440532013000.", "call 555-123-4567 now", "order 555-123-4567", "number 555-123-4567",
        "SSN 123-45-6789", "part 123-45-6789", "SSN 000-45-6789",
    ]
    kinds = [[k for k, *_ in spans] for spans in found(spark, texts)]
    assert kinds == [["iban"], [], ["iban"], ["local_phone"], [], [], ["tax_id"], [], []]
    (near,), (against,) = found(spark, ["my card 4111111111111111", "order 4111111111111111"])
    assert near[0] == against[0] == "card" and near[3] > against[3]


def test_very_long_texts(spark):
    many = "x@y.zz " * 3000
    texts = ["a" * 200_000, "1" * 100_000, "a@b" + ".c" * 60_000, "1 11 " * 20_000, "+1" + " " * 100_000, many]
    spans = found(spark, texts)
    assert [len(s) for s in spans] == [0, 0, 1, 0, 0, 3000]
    assert spans[5][-1][1:3] == (len(many) - 7, len(many) - 1)


def test_redaction_and_defined_cases(spark):
    df = spark.createDataFrame([(1, "mail a@b.cc and 10.0.0.1!", "x"), (1, "mail a@b.cc and 10.0.0.1!", "x"), (2, None, None), (3, "", None)], "doc_id long, text string, pii_spans string")
    done = pii.find_spans(df).withColumn("clean", pii.redact(F.col("text"), F.col("pii_spans"))).orderBy("doc_id").collect()
    assert [r.clean for r in done] == ["mail <EMAIL> and <IP>!"] * 2 + [None, ""]
    assert pii.find_spans(df.limit(0)).count() == 0
