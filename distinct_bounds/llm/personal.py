"""Personal data: labelers vote on spans, expectation-maximisation weighs them and trains a span classifier."""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from distinct_bounds.llm.common import col, materialize, table, text_udf, with_outputs

KINDS = ("email", "ip", "card", "phone")
#: A further kind that only the method finds, and that is told apart from personal data in the output.
SECRET = len(KINDS)
OUTPUTS = ("n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans")

# The forms of the base spans, and short lists that labelers look up.
MAIL_RIGHT = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
MAIL_LEFT = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
ADDRESS = re.compile(r"(?<![0-9])[0-9]++\.([0-9]++)\.([0-9]++)\.([0-9]++)")
CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
LOOSE_MAIL = re.compile(r"[A-Za-z0-9._%+-]+ ?[(\[] ?at ?[)\]] ?[A-Za-z0-9-]+(?: ?(?:[(\[] ?dot ?[)\]]|\.) ?[A-Za-z0-9-]+)+")
LOOSE_ADDRESS = re.compile(r"(?<![0-9A-Fa-f:])[0-9A-Fa-f]{1,4}(?::[0-9A-Fa-f]{1,4}){7}(?![0-9A-Fa-f:])")
LOOSE_CARD = re.compile(r"(?<![0-9A-Za-z.])(?:[0-9]{14,19}|[0-9]{4}([ -])[0-9]{4}\1[0-9]{4}\1[0-9]{2,7})(?![0-9A-Za-z])")
LOOSE_PHONE = re.compile(r"(?<![0-9A-Za-z+.-])(?:\+[0-9]{1,3}[ .-])?\(?[0-9]{2,4}\)?(?:[ .-][0-9]{2,4}){2,4}(?![0-9A-Za-z])")
ASSIGNED = re.compile(r"[=:] ?[\"']?([A-Za-z0-9+/_.~-]{8,})")
KEY_ID = re.compile(r"(?<![A-Za-z0-9])(?:AKIA|ASIA)[0-9A-Z]{16}(?![A-Za-z0-9])")
LAST_WORD = re.compile(r"([A-Za-z][A-Za-z0-9_-]*)[\"']? ?$")
ENDING = re.compile(r"([A-Za-z0-9-]+)[ )\]]*$")
DOMAINS = frozenset("com org net edu gov info biz io de fr es it nl uk eu us ca au ch at be".split())
CALLING = ("1", "20", "27", "30", "31", "32", "33", "34", "39", "41", "43", "44", "45", "46", "47", "48", "49", "52", "54", "55", "61", "81", "82", "86", "90", "91")
CUES = {
    "email": frozenset("mail email e-mail contact write courriel correo kontakt adresse".split()),
    "ip": frozenset("ip host server address from client login adresse servidor".split()),
    "card": frozenset("card visa mastercard credit carte karte tarjeta payment iban".split()),
    "phone": frozenset("phone tel telephone call mobile fax cell fon telefon telefono telephoner".split()),
    "secret": frozenset("password passwd pwd passphrase token secret key apikey api_key api-key access_key auth bearer credential".split()),
}
DENIALS = frozenset("version isbn issn order invoice sku build release figure page total hash id ticket serial part ref".split())
FILLERS = ("example", "changeme", "xxxx", "0000", "1234567", "your", "placeholder")
BEFORE = re.compile(r"[\w-]+")


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        d = int(d) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def digits_of(text: str) -> str:
    return "".join(c for c in text if "0" <= c <= "9")


def mails(text: str) -> Iterator[tuple[int, int]]:
    """Around each @, the run of allowed characters before it and a dotted name after it."""
    done, at = 0, text.find("@")
    while at >= 0:
        right = MAIL_RIGHT.match(text, at)
        if right:
            start = at
            while start > done and text[start - 1] in MAIL_LEFT:
                start -= 1
            if start < at:
                done = right.end()
                yield start, done
        at = text.find("@", max(at + 1, done))


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the base spans, in order."""
    found = [(a, 0, b) for a, b in mails(text)]
    for m in ADDRESS.finditer(text):
        parts = [p.lstrip("0") for p in m.group().split(".")]
        if all(len(p) <= 3 and int(p or 0) <= 255 for p in parts):
            found.append((m.start(), 1, m.end()))
    for m in CARD.finditer(text):
        d = digits_of(m.group())
        if 14 <= len(d) <= 19 and luhn(d):
            found.append((m.start(), 2, m.end()))
    if "+" in text:
        for m in PHONE.finditer(text):
            if 10 <= len(digits_of(m.group())) <= 15:
                found.append((m.start(), 3, m.end()))
    return sorted(found)


def other_spans(text: str, base: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """Spans of a looser form, in order of place, that overlap no base span nor an earlier looser one."""
    found: list[tuple[int, int, int]] = []
    loose = [(0, LOOSE_MAIL)] if "(at" in text or "[at" in text or "( at" in text or "[ at" in text else []
    for kind, form in (*loose, (1, LOOSE_ADDRESS), (2, LOOSE_CARD), (3, LOOSE_PHONE)):
        for m in form.finditer(text):
            n = len(digits_of(m.group()))
            if (kind == 2 and not 14 <= n <= 19) or (kind == 3 and not 9 <= n <= 15):
                continue
            found.append((m.start(), kind, m.end()))
    found += [(m.start(), SECRET, m.end()) for m in KEY_ID.finditer(text)]
    for m in ASSIGNED.finditer(text):
        if any("0" <= c <= "9" for c in m.group(1)):
            found.append((m.start(1), SECRET, m.end(1)))
    out, taken, at, last = [], sorted((a, b) for a, _, b in base), 0, 0
    for a, kind, b in sorted(found, key=lambda x: (x[0], x[1])):
        while at < len(taken) and taken[at][1] <= a:
            at += 1
        if a >= last and not (at < len(taken) and taken[at][0] < b):
            out.append((a, kind, b))
            last = b
    return out


def spread_of(text: str) -> float:
    """Bits a character by the text's own frequencies."""
    n = len(text)
    return -sum(k / n * math.log2(k / n) for k in Counter(text).values())


def votes(text: str, span: tuple[int, int, int]) -> str:
    """One sign for each labeler: + for personal data, - against, 0 where it has nothing to say.

    In order: the neighbours of the span, the gazetteers, cue words before it, words that
    deny it, the checksum or the count of digits, and its layout. No labeler knows by which
    form a span was found.
    """
    start, kind, end = span
    body, digits = text[start:end], digits_of(text[start:end])
    left, right = text[max(0, start - 1) : start], text[end : end + 1]
    context = text[max(0, start - 48) : start]
    before = [w.lower() for w in BEFORE.findall(context)][-4:]
    glued = bool(left) and (left.isalnum() or left in "\"'_=/#") or bool(right) and (right.isalnum() or right in "\"'_=/#")
    near = "-" if glued else "+"
    cue = "+" if any(w in CUES[KINDS[kind] if kind < SECRET else "secret"] for w in before) else "0"
    deny = "-" if any(w in DENIALS for w in before) else "+"
    if kind == 0:
        ending = ENDING.search(body)
        known = "+" if ending and ending.group(1).lower() in DOMAINS else "-"
        check = "+" if any(c.isalpha() for c in body.partition("@")[0].partition(" ")[0]) else "-"
        layout = "-" if len(body) > 80 or body.startswith(("-", "%")) else "+"
    elif kind == 1:
        known = "-" if body.startswith(("0.", "127.", "255.", "10.")) else "+"
        check = "+" if body.count(".") == 3 or body.count(":") == 7 else "-"
        layout = "-" if left == "." or (right == "." and text[end + 1 : end + 2].isdigit()) else "+"
    elif kind == 2:
        known = "+" if digits[:1] in "3456" else "-"
        check = "+" if luhn(digits) else "-"
        layout = "+" if body.isdigit() or len({c for c in body if not c.isdigit()}) == 1 else "-"
    elif kind == 3:
        known = "+" if body.startswith("+") and digits.startswith(CALLING) else "-" if body.startswith("+") else "0"
        check = "+" if 9 <= len(digits) <= 15 else "-"
        layout = "+" if "(" in body or body.startswith(("+", "0")) else "0"
    else:
        name = LAST_WORD.search(context[:-1] if context[-1:] in "=:" else context.rstrip("\"' ").removesuffix("=").removesuffix(":").rstrip())
        assigned = name is not None and any(w in CUES["secret"] for w in (name.group(1).lower(), *re.split("[_-]", name.group(1).lower())))
        near = "+" if assigned else "0"
        known = "+" if KEY_ID.fullmatch(body) else "0"
        check = "+" if spread_of(body) >= 2.9 else "-"
        layout = "-" if any(f in body.lower() for f in FILLERS) or body.count(".") > 1 or "//" in body else "+" if len(body) >= 12 else "0"
    return near + known + cue + deny + check + layout


def shape(text: str, span: tuple[int, int, int]) -> tuple[int, int, int]:
    """Coarse looks of a span: counts of digits and of separators in a few steps, and its length."""
    body = text[span[0] : span[2]]
    n = len(digits_of(body))
    marks = sum(not c.isalnum() for c in body)
    return min(n // 4, 5), min(marks, 5), min((span[2] - span[0]) // 8, 5)


SIGNS = "-0+"
LABELERS = 6
SHAPES = (6, 6, 6)
KIND_WIDTH = 1 + LABELERS * len(SIGNS)
INPUTS = (SECRET + 1) * KIND_WIDTH + sum(SHAPES)


def inputs_of(text: str, span: tuple[int, int, int]) -> list[int]:
    """Places of a span's ones among the classifier's inputs: its kind, each vote for this kind, each step of the shape."""
    first = span[1] * KIND_WIDTH
    out = [first] + [first + 1 + j * len(SIGNS) + SIGNS.index(c) for j, c in enumerate(votes(text, span))]
    at = (SECRET + 1) * KIND_WIDTH
    for n, step in zip(SHAPES, shape(text, span), strict=True):
        out.append(at + step)
        at += n
    return out


def spans_of(text: str | None) -> list[dict]:
    """All candidate spans with what is known of them."""
    if not text:
        return []
    raw = text.encode("utf-8", "surrogatepass")
    if len(raw.translate(None, b"0123456789@[(")) == len(raw):
        return []
    base = base_spans(text)
    found = [(x, True) for x in base] + [(x, False) for x in other_spans(text, base)]
    return [{"start": x[0], "kind": x[1], "end": x[2], "base": strict, "inputs": inputs_of(text, x)} for x, strict in found]


@dataclass(frozen=True)
class PersonalSpec:
    """A span that is not a base one is added where the classifier's chance reaches threshold.

    doubt is how many spans' worth of weight BELIEF has; without it the two classes could change places.
    """

    threshold: float = 0.9
    rounds: int = 200
    steps: int = 800
    l2: float = 1e-5
    doubt: float = 20.0


# What each labeler, in the order of votes(), is believed to say (-, 0, +) of spans that are not
# personal data and of those that are, before any is seen.
BELIEF = np.array([
    [[0.40, 0.10, 0.50], [0.05, 0.10, 0.85]],
    [[0.40, 0.40, 0.20], [0.05, 0.45, 0.50]],
    [[0.02, 0.93, 0.05], [0.02, 0.48, 0.50]],
    [[0.50, 0.02, 0.48], [0.02, 0.02, 0.96]],
    [[0.70, 0.05, 0.25], [0.03, 0.02, 0.95]],
    [[0.30, 0.40, 0.30], [0.10, 0.35, 0.55]],
])


def weigh(inputs: np.ndarray, count: np.ndarray, spec: PersonalSpec) -> tuple[np.ndarray, np.ndarray]:
    """Expectation-maximisation over patterns, rows of places of ones, and their counts: how each labeler speaks of
    either class of each kind, as (kind, labeler, class, sign), and each pattern's chance of being personal data.

    No pattern's class is known, those of base spans neither.
    """
    kind = inputs[:, 0] // KIND_WIDTH
    said = inputs[:, 1 : 1 + LABELERS] - inputs[:, :1] - 1 - np.arange(LABELERS) * len(SIGNS)
    first = sum(np.log(BELIEF[j, 1, said[:, j]] / BELIEF[j, 0, said[:, j]]) for j in range(LABELERS))
    chance = 1 / (1 + np.exp(-first))
    speech = np.zeros((SECRET + 1, LABELERS, 2, len(SIGNS)))
    for _ in range(spec.rounds):
        gain = np.zeros(len(inputs))
        for k in range(SECRET + 1):
            of = kind == k
            if not of.any():
                continue
            mass = np.stack([count[of] * (1 - chance[of]), count[of] * chance[of]])
            prior = (mass[1].sum() + 1) / (mass.sum() + 2)
            gain[of] = np.log(prior / (1 - prior))
            for j in range(LABELERS):
                heard = np.stack([np.bincount(said[of, j], m, len(SIGNS)) for m in mass]) + spec.doubt * BELIEF[j]
                speech[k, j] = heard / heard.sum(axis=1, keepdims=True)
                gain[of] += np.log(speech[k, j, 1, said[of, j]] / speech[k, j, 0, said[of, j]])
        fresh = 1 / (1 + np.exp(-np.clip(gain, -40, 40)))
        done = np.abs(fresh - chance).max() < 1e-9
        chance = fresh
        if done:
            break
    return speech, chance


def classify(inputs: np.ndarray, count: np.ndarray, chance: np.ndarray, spec: PersonalSpec) -> np.ndarray:
    """The span classifier: weights of a logistic regression on the inputs, to the labelers' joint chances."""
    x = np.zeros((len(inputs), INPUTS))
    np.put_along_axis(x, inputs, 1, axis=1)
    weight = np.sqrt(count.astype(float))
    weight /= weight.sum()
    w, first, second = np.zeros(INPUTS), np.zeros(INPUTS), np.zeros(INPUTS)
    for step in range(1, spec.steps + 1):
        grad = x.T @ (weight * (1 / (1 + np.exp(-np.clip(x @ w, -40, 40))) - chance)) + spec.l2 * w
        first, second = 0.9 * first + 0.1 * grad, 0.99 * second + 0.01 * grad * grad
        w -= 0.2 / np.sqrt(step) * (first / (1 - 0.9**step)) / (np.sqrt(second / (1 - 0.99**step)) + 1e-9)
    return w


def train(seen: DataFrame, spec: PersonalSpec) -> np.ndarray:
    """The classifier's weights from the counts of all patterns of the table; the driver gets a row for each of the
    patterns, of which there can be only so many, whatever the table."""
    counted = seen.select(F.explode("found").alias("s")).groupBy("s.inputs").agg(F.count("*").alias("n")).collect()
    counted.sort(key=lambda r: r["inputs"])
    if not counted:
        return np.zeros(INPUTS)
    inputs, count = np.array([r["inputs"] for r in counted]), np.array([r["n"] for r in counted], float)
    return classify(inputs, count, weigh(inputs, count, spec)[1], spec)


def find_spans(docs: DataFrame, spec: PersonalSpec = PersonalSpec(), text_col: str = "text", carry: Sequence[str] | None = None) -> DataFrame:
    """docs, or its columns `carry`, with `found`, an array of (start, kind, end, base, chance): the base spans and those that the method adds.

    Places are code points, ends exclusive; kind is the place in KINDS, or SECRET; the array
    is in order of start, then kind. A null or empty text has none, and an empty table gives
    an empty one. The candidates of every text are written to the shared folder; labelers are
    weighed and the classifier is trained on the counts of their patterns over the whole
    table, and it is applied as a sum of looked-up weights. Every row is returned, repeated ones too.
    """
    inner = "array<struct<start:int,kind:int,end:int,base:boolean,inputs:array<int>>>"
    seen = with_outputs(docs, text_udf(f"found {inner}", ("found",), lambda: lambda texts: ([spans_of(t) for t in texts],)), text_col, ("found",))
    names = [c for c in (docs.columns if carry is None else carry) if c.lower() != "found"]
    seen = materialize(seen.select(*[col(c) for c in names], "found"), "spans")
    weights = F.lit([float(w) for w in train(seen, spec)])

    def chance(s: Column) -> Column:
        return 1 / (1 + F.exp(-F.aggregate(s["inputs"], F.lit(0.0), lambda total, i: total + F.element_at(weights, i + 1))))

    told = F.transform("found", lambda s: F.struct(s["start"].alias("start"), s["kind"].alias("kind"), s["end"].alias("end"), s["base"].alias("base"), chance(s).alias("chance")))
    return seen.withColumn("found", F.array_sort(F.filter(told, lambda s: s["base"] | (s["chance"] >= spec.threshold))))


def written(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in (*KINDS, "secret")])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")


def count_of(kind: int) -> Column:
    return F.size(F.filter("found", lambda s: s["base"] & (s["kind"] == kind)))


def op6_personal(spark, sf_dir: str) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans for every document; counts are of base spans.

    n_secret and secrets are passwords, tokens and keys that the method finds, which are no
    personal data and not among spans; n_found counts all spans and secrets.
    """
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = find_spans(docs, carry=("doc_id",))
    base, secret = F.filter("found", lambda s: s["base"]), F.filter("found", lambda s: s["kind"] == SECRET)
    counts = [count_of(k).cast("bigint").alias(f"n_{name}") for k, name in enumerate(KINDS)]
    personal = F.filter("found", lambda s: s["kind"] < SECRET)
    more = [F.size(secret).cast("bigint").alias("n_secret"), written(secret).alias("secrets"), F.size("found").cast("bigint").alias("n_found")]
    return found.select("doc_id", *counts, F.sha2(written(base), 256).alias("base_sha256"), written(personal).alias("spans"), *more)
