import hashlib
import math
import random
import re
from collections import Counter

import numpy as np

from distinct_bounds.llm import personal
from distinct_bounds.llm.personal import KINDS, base_spans, find_spans, luhn

FORMS = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def plain(text):
    """The base spans by their printed forms."""
    out = []
    for k, (kind, form) in enumerate(FORMS.items()):
        for m in re.finditer(form, text):
            digits = re.sub(r"[^0-9]", "", m.group())
            good = {
                "email": True,
                "ip": kind == "ip" and all(int(x) <= 255 for x in m.group().split(".")),
                "card": 14 <= len(digits) <= 19 and luhn(digits),
                "phone": 10 <= len(digits) <= 15,
            }[kind]
            if good:
                out.append((m.start(), k, m.end()))
    return sorted(out)


def test_base_spans_equal_the_plain_forms():
    rng = random.Random(5)
    pieces = ["a@b.c", "x.y+z@mail7.example.com", "@", ".", "1.2.3.4", "256.1.1.1", "4111 1111 1111 1111", "4111-1111-1111-1112", "+1 (017) 555-7713", "+", " ", "-", "0", "97.51.17.173", "é", "(", "a@b.c@d.e", "\n", "00000.1.2.3", "7", "word"]
    for _ in range(3000):
        text = "".join(rng.choice(pieces) for _ in range(rng.randint(1, 14)))
        assert base_spans(text) == plain(text), text


def test_query_shape_and_edges(spark):
    card = "4111111111111111"
    rows = [(1, f"pay {card} now é a@b.com", 7), (2, None, 7), (3, "", 7), (None, "10.0.0.1", None), (1, f"pay {card} now é a@b.com", 7), (4, "x" * 200_000 + " +1 (017) 555-7713", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, found int")
    got = find_spans(docs).collect()
    assert len(got) == len(rows)
    by = {r["doc_id"]: [(KINDS[s["kind"]], s["start"], s["end"]) for s in r["found"]] for r in got}
    assert by[1] == [("card", 4, 20), ("email", 27, 34)]
    assert by[2] == by[3] == []
    assert by[None] == [("ip", 0, 8)]
    assert by[4] == [("phone", 200_001, 200_018)]
    assert find_spans(docs.limit(0)).count() == 0


def plain_weigh(patterns, spec, rounds):
    """The same iterations, pattern by pattern and labeler by labeler."""
    said = {p: [(v - p[0] - 1 - 3 * j) for j, v in enumerate(p[1:7])] for p in patterns}
    chance = {}
    for p in patterns:
        odds = math.prod(personal.BELIEF[j][1][v] / personal.BELIEF[j][0][v] for j, v in enumerate(said[p]))
        chance[p] = odds / (1 + odds)
    for _ in range(rounds):
        fresh = {}
        for p in patterns:
            same = [q for q in patterns if q[0] == p[0]]
            yes, no = sum(patterns[q] * chance[q] for q in same), sum(patterns[q] * (1 - chance[q]) for q in same)
            odds = (yes + 1) / (no + 1)
            for j in range(6):
                heard = []
                for share in (lambda q: 1 - chance[q], lambda q: chance[q]):
                    y = len(heard)
                    at = [sum(patterns[q] * share(q) for q in same if said[q][j] == v) + spec.doubt * personal.BELIEF[j][y][v] for v in range(3)]
                    heard.append(at[said[p][j]] / sum(at))
                odds *= heard[1] / heard[0]
            fresh[p] = odds / (1 + odds)
        chance = fresh
    return chance


def test_weighing_equals_a_plain_loop():
    rng = random.Random(2)
    patterns = {}
    for _ in range(60):
        first = rng.randrange(5) * personal.KIND_WIDTH
        patterns[(first, *(first + 1 + 3 * j + rng.randrange(3) for j in range(6)), 95, 101, 107)] = rng.randint(1, 90)
    spec = personal.PersonalSpec(rounds=7)
    keys = sorted(patterns)
    _, chance = personal.weigh(np.array(keys), np.array([patterns[k] for k in keys], float), spec)
    want = plain_weigh(patterns, spec, 7)
    assert np.allclose(chance, [want[k] for k in keys], atol=1e-9)


def planted():
    """(text, spans that should be added, spans that should not) with base spans among them."""
    rng = random.Random(9)
    words = "the river holds its bank while small boats drift slowly past".split()

    def filler():
        return " ".join(rng.choice(words) for _ in range(rng.randint(4, 12)))

    for i in range(1200):
        text, good, bad = filler(), [], []
        kind = i % 6
        number = f"0{rng.randint(20, 99)} {rng.randint(1000, 9999)} {rng.randint(1000, 9999)}"
        token = hashlib.sha256(str(i).encode()).hexdigest()[:24]
        cue, span, sort, want = [
            (rng.choice(["contact", "write", "mail"]), f"jo{i}.doe (at) example{i % 7} (dot) {rng.choice(['com', 'org', 'de'])}", 0, True),
            (rng.choice(["phone", "call", "tel"]), number, 3, True),
            (rng.choice(["order", "invoice", "version", "isbn"]), number, 3, False),
            (rng.choice(["mail", "holds"]), f"u{i}@mail{i % 5}.example.com", None, None),
            (rng.choice(["password", "api_key"]) + "=", token, personal.SECRET, True),
            ("number", "".join(str(rng.randint(0, 9)) for _ in range(16)), 2, False),
        ][kind]
        text += f" {cue}{'' if cue.endswith('=') else ' '}"
        if want is not None and not (sort == 2 and luhn(span)):
            (good if want else bad).append((len(text), sort, len(text) + len(span)))
        yield text + span + " " + filler(), good, bad


def test_added_spans_are_those_planted(spark):
    cases = list(planted())
    docs = spark.createDataFrame([(i, t) for i, (t, _, _) in enumerate(cases)], "doc_id long, text string")
    got = {r["doc_id"]: {(s["start"], s["kind"], s["end"]) for s in r["found"] if not s["base"]} for r in find_spans(docs).collect()}
    for sort in (0, 3, personal.SECRET):
        want = {(i, g) for i, (_, good, _) in enumerate(cases) for g in good if g[1] == sort}
        found = {(i, g) for i, gs in got.items() for g in gs if g[1] == sort}
        assert len(want) >= 200 and len(want & found) >= 0.9 * len(want), (sort, len(want & found))
        assert len(want & found) >= 0.9 * len(found), (sort, len(found))
    refused = {(i, b) for i, (_, _, bad) in enumerate(cases) for b in bad}
    assert len(refused) >= 300 and len({(i, b) for i, b in refused if b in got[i]}) <= 0.1 * len(refused)
    for r in find_spans(docs).collect():
        assert {(s["start"], s["kind"], s["end"]) for s in r["found"] if s["base"]} == set(base_spans(cases[r["doc_id"]][0]))


def test_spans_equal_a_plain_run(spark):
    texts = [t for t, _, _ in planted()][:300]
    seen = Counter(tuple(s["inputs"]) for t in texts for s in personal.spans_of(t))
    keys, spec = sorted(seen), personal.PersonalSpec()
    inputs, count = np.array(keys), np.array([seen[k] for k in keys], float)
    weights = personal.classify(inputs, count, personal.weigh(inputs, count, spec)[1], spec)
    want = []
    for t in texts:
        kept = [s for s in personal.spans_of(t) if s["base"] or 1 / (1 + math.exp(-sum(weights[i] for i in s["inputs"]))) >= spec.threshold]
        want.append(sorted((s["start"], s["kind"], s["end"]) for s in kept))
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: [(s["start"], s["kind"], s["end"]) for s in r["found"]] for r in find_spans(docs).collect()}
    assert [got[i] for i in range(len(texts))] == want


def test_query_on_a_table(spark, tmp_path):
    docs = spark.createDataFrame([(5, "mail a@b.com or 1.2.3.4"), (6, "no name"), (7, None)], "doc_id long, text string")
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    made = personal.op6_personal(spark, str(tmp_path))
    assert made.count() == 3 and made.filter("doc_id > 5").agg({"n_found": "sum"}).first()[0] == 0
    row = made.filter("doc_id = 5").first()
    text = "email:5:12,ip:16:23"
    assert (row["n_email"], row["n_ip"], row["n_card"], row["n_phone"]) == (1, 1, 0, 0)
    assert row["spans"] == text and row["base_sha256"] == hashlib.sha256(text.encode()).hexdigest()
