import hashlib
import random
import re

from pyspark.sql import functions as F

from rarespan.llm.pii import digest, find_pii, luhn, mod97, redact

PATTERNS = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def base(text):
    out = []
    for k, (kind, p) in enumerate(PATTERNS.items()):
        for m in re.finditer(p, text or ""):
            d = re.sub("[^0-9]", "", m[0])
            ok = {
                "email": True,
                "ip": kind == "ip" and all(int(x) <= 255 for x in m[0].split(".")),
                "card": 12 <= len(d) <= 19 and luhn(d),
                "phone": 9 <= len(d) <= 15,
            }[kind]
            if ok:
                out.append((m.start(), k, f"{kind}:{m.start()}:{m.end()}"))
    return [x[2] for x in sorted(out)]


def test_base_spans_equal_plain_patterns(spark):
    rnd = random.Random(2)
    parts = ["a.b%", "@", "x-1", ".", "é", " ", "+", "12", "4539578763621486", "(017) 555", "-", "\n", "1.2.3.4", "300.1.1.1", "+1 (212) 555-7788", "me@ex.co.uk", "00009.8.7.6.5", "DE89 3704 0044 0532 0130 00", "𝟘x"]
    rows = [(i, "".join(rnd.choice(parts) for _ in range(rnd.randrange(40)))) for i in range(600)]
    rows += [(600, None), (601, ""), (5, "twice a@b.c"), (5, "twice a@b.c")]
    got = digest(find_pii(spark.createDataFrame(rows, "doc_id long, text string"))).collect()
    want = sorted((i, ",".join(base(t))) for i, t in rows)
    assert sorted((r.doc_id, ",".join(s for s in r.spans.split(",") if s.split(":")[0] in PATTERNS)) for r in got) == want
    hashes = sorted((i, hashlib.sha256(b.encode()).hexdigest()) for i, b in want)
    assert sorted((r.doc_id, r.base_sha256) for r in got) == hashes
    assert sum(r.n_email + r.n_ip + r.n_card + r.n_phone for r in got) == sum(len(base(t)) for _, t in rows)


def test_added_kinds_and_checksums(spark):
    assert mod97("DE89370400440532013000") and not mod97("DE88370400440532013000")
    rows = [(1, "iban DE89 3704 0044 0532 0130 00 ok"), (2, 'token = "cf1d64a9a4cd9723e1f4eafc27395915e6868ffa" x'), (3, "call 017 555 77134 now"), (4, "item 017 555 77134 now"), (5, "a_very_long_identifier_name_2 x")]
    got = {r.doc_id: r.spans for r in find_pii(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert [s.kind for s in got[1]] == ["iban"]
    assert [s.kind for s in got[2]] == ["secret"]
    assert [s.kind for s in got[3]] == ["national_phone"]
    assert got[4] == [] and got[5] == []


def test_redact_keeps_rows_and_columns(spark):
    rows = [(1, "é a@b.co +1 (212) 555-7788 x", "s", 9), (2, None, None, None), (3, "plain", "s", 5)]
    df = spark.createDataFrame(rows, "doc_id long, text string, kind string, score long")
    got = {r.doc_id: r for r in redact(df).collect()}
    assert got[1].text == "é <email> <phone> x" and got[2].text is None and got[3].text == "plain"
    assert redact(df).columns == df.columns
    assert redact(df.limit(0)).collect() == []


def test_very_long_runs(spark):
    n = 100_000
    rows = ["0" * n + ".1.1.1", "0" * n + "...", "a" * n + "@", "a@" * n, "1." * n, "1" * n, "+1" + " " * n, "+1" * n, "1 " * n, "A" * n + " DE89", "1 2 3 4 5 6 7 8 9" + " " * n, "x@a.b" * (n // 5), "é" * n + " a@b.c", "0000000255.1.1.1", "A1_" * n]
    df = spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string").withColumn("spans", F.lit("x"))
    got = {r.doc_id: r for r in digest(find_pii(df)).collect()}
    assert len(got) == len(rows)
    assert (got[0].n_ip, got[1].n_ip, got[2].n_email, got[3].n_email) == (1, 0, 0, 0)
    assert got[11].n_email > 0 and got[12].spans == f"email:{n + 1}:{n + 6}" and got[13].n_ip == 1
    assert redact(df).count() == len(rows)
