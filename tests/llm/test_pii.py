import hashlib
import re

import numpy as np
import pytest

from linefault.llm import pii

#: The published expressions, as they are.
PUBLISHED = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}
CASES = ["", None, "a@b.c@d.e", "x1.2.3.4.5.6.7.8", "a@b.cd_e@f.g", "12345678901234567890 4111 1111 1111 1111", "4111-1111-1111-1111 +1 (202) 555-0143 ()", "+12025550143+13", "é😀 a.b+c@x-y.zz 300.1.1.1 1.1.1.1", "a@@b.c", "@b.c", "1" * 400 + "." + "2.2.2", "a." * 900 + "@b" + ".c" * 900, "1.1.1.1@x.com 00000000255.1.1.1", " - 4111 1111-1111 1111-", "+1 . . . . 2025550143..1.2.3.4", "4111111111111111 4111111111111112", "a@b.c\na@b.c a@b.c,5.5.5.5"]


def luhn(digits):
    total = 0
    for i, c in enumerate(reversed(digits)):
        v = int(c) * (1 + i % 2)
        total += v - 9 * (v > 9)
    return total % 10 == 0


def base(text):
    out, counts = [], []
    for rank, (kind, pattern) in enumerate(PUBLISHED.items()):
        n = 0
        for m in re.finditer(pattern, text or ""):
            digits = re.sub("[^0-9]", "", m.group())
            if kind == "ip" and any(len(p.lstrip("0")) > 3 or int(p) > 255 for p in m.group().split(".")):
                continue
            if kind == "card" and not (14 <= len(digits) <= 19 and luhn(digits)) or kind == "phone" and not 10 <= len(digits) <= 15:
                continue
            out.append((m.start(), rank, m.end(), kind))
            n += 1
        counts.append(n)
    spans = ",".join(f"{k}:{a}:{b}" for a, _, b, k in sorted(out))
    return counts, spans, hashlib.sha256(spans.encode()).hexdigest()


def same(df, texts):
    rows = pii.find_personal_data(df).collect()
    assert len(rows) == len(texts)
    for r in rows:
        counts, _, digest = base(texts[r.doc_id])
        assert [r.n_email, r.n_ip, r.n_card, r.n_phone] == counts and r.base_sha256 == digest


def test_cases(spark):
    same(spark.createDataFrame(list(enumerate(CASES)), "doc_id long, text string"), dict(enumerate(CASES)))


def test_ip_parts_of_zero(spark):
    texts = dict(enumerate(["10.0.0.1", "at 0.0.0.0, 192.168.0.12", "000.1.1.1 00.0.000.0255", "0256.0.0.1 1.0.0.256"]))
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    same(df, texts)
    assert {r.doc_id: r.n_ip for r in pii.find_personal_data(df).collect()} == {0: 1, 1: 2, 2: 2, 3: 0}
    assert {r.doc_id: r.text for r in pii.sanitise(df).collect()}[1] == "at [IP], [IP]"


def test_whole_table(spark, sf):
    df = spark.read.parquet(f"{sf}/documents.parquet")
    same(df, {r.doc_id: r.text for r in df.collect()})


def test_odd_rows(docs_of, odd):
    assert pii.find_personal_data(docs_of(odd)).count() == len(odd)
    assert pii.find_personal_data(docs_of([])).count() == 0


@pytest.fixture(scope="module")
def secret(spark):
    rows = [(i, f"contact Zorblax number {i} at zorb@secret.org today\nplain filler line {i} common words") for i in range(8)]
    return spark.createDataFrame(rows + [(100 + i, f"filler number contact today common words {i} again") for i in range(400)], "doc_id long, text string")


def test_disclosing_terms(secret):
    found = pii.disclosing_terms(secret).collect()
    assert [(r.term, r.entity, r.n_joint, r.n_term) for r in found] == [("zorblax", "email:zorb@secret.org", 8, 8)]
    assert found[0].pmi == pytest.approx(found[0].ic)


def test_sanitised_text(secret):
    clean = {r.doc_id: r.text for r in pii.sanitise(secret).collect()}
    assert clean[3] == "contact [TERM] number 3 at [EMAIL] today\nplain filler line 3 common words"
    assert clean[105] == "filler number contact today common words 5 again"


def test_copies_are_no_evidence(spark):
    rows = [(i, "the same Zorblax line with zorb@secret.org in it") for i in range(50)]
    assert pii.disclosing_terms(spark.createDataFrame(rows, "doc_id long, text string")).count() == 0


def terms_by_hand(texts, support=pii.SUPPORT, disclosure=pii.DISCLOSURE):
    """Disclosing terms by counting over distinct lines, with the published expressions."""
    lines = {x for t in texts for x in (t or "").split("\n") if x}
    word = lambda t: {w.lower() for w in re.findall(r"[^\W\d_]{4,}", t)}
    held, entities, heard = {}, {}, {}
    for line in lines:
        found = set()
        for start, _, end, kind in [s for s in spans_of(line)]:
            found.add(f"{kind}:{line[start:end]}")
        bare = line
        for kind in PUBLISHED:
            bare = re.sub(PUBLISHED[kind], " ", bare)
        held[line] = (found, word(bare))
        for e in found:
            entities[e] = entities.get(e, 0) + 1
        for w in word(line):
            heard[w] = heard.get(w, 0) + 1
    out = set()
    for e, n in entities.items():
        if n < support:
            continue
        for w in set().union(*[t for f, t in held.values() if e in f]):
            both = sum(e in f and w in t for f, t in held.values())
            own = np.log2(len(lines) / n)
            if both >= support and own > 0 and np.log2(len(lines) * both / (heard[w] * n)) >= disclosure * own:
                out.add((w, e, both, heard[w], n))
    return out


def spans_of(text):
    spans = base(text)[1]
    for part in spans.split(",") if spans else []:
        kind, a, b = part.split(":")
        yield int(a), 0, int(b), kind


def planted(rng):
    people = [(f"agent{chr(97 + i)}zz", f"user{i}@mail{i}.org") for i in range(6)]
    rows = []
    for i in range(260):
        name, mail = people[int(rng.integers(0, 6))]
        lines = [f"word{chr(97 + int(rng.integers(0, 26)))}abc filler number {i} text" for _ in range(3)]
        if rng.random() < 0.4:
            lines.append(f"note {i} {name.title() if rng.random() < 0.9 else 'somebody'} wrote {mail} about {chr(97 + int(rng.integers(0, 26)))}things")
        if rng.random() < 0.1:
            lines.append(f"note {i} {people[0][0]} alone without address")
        rows.append((i, "\n".join(lines)))
    return rows + [(300 + i, rows[3][1]) for i in range(40)] + [(400, None), (401, "")]


def test_terms_and_spans_against_counting(spark):
    """Counts, thresholds and the spans string, over a corpus with copies."""
    rows = planted(np.random.default_rng(7))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = terms_by_hand([t for _, t in rows])
    assert {(r.term, r.entity, r.n_joint, r.n_term, r.n_entity) for r in pii.disclosing_terms(df).collect()} == want and len(want) > 2
    terms = {w for w, *_ in want}
    got = {r.doc_id: r.spans for r in pii.find_personal_data(df).collect()}
    for i, text in rows:
        every = [(a, pii.KINDS.index(k), b, k) for a, _, b, k in spans_of(text)]
        every += [(m.start(), 4, m.end(), "term") for m in re.finditer(r"[^\W\d_]{4,}", text or "") if m.group().lower() in terms]
        assert got[i] == ",".join(f"{k}:{a}:{b}" for a, _, b, k in sorted(every))


def test_random_addresses(spark):
    rng = np.random.default_rng(11)
    texts = {i: " ".join(".".join(f"{int(rng.integers(0, 300)):0{int(rng.integers(1, 5))}d}" for _ in range(int(rng.integers(3, 6)))) for _ in range(20)) for i in range(60)}
    same(spark.createDataFrame(list(texts.items()), "doc_id long, text string"), texts)


def test_no_python(docs_of, odd):
    plan = pii.find_personal_data(docs_of(odd))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Pandas" not in plan and "Arrow" not in plan


def test_sanitise_odd_rows(docs_of, odd):
    df = docs_of(odd)
    out = pii.sanitise(df)
    assert out.columns == df.columns and sorted(map(str, out.collect())) == sorted(map(str, df.collect()))
    assert pii.sanitise(docs_of([])).count() == 0
