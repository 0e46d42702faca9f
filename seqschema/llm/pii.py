"""Personal data by exact base patterns and a semi-Markov conditional random field over whole spans.

The base patterns (email, ip, card, phone) are exact and always stay. The model then looks for spans the patterns miss:
spoken addresses, national phone forms, other card lengths, long IP addresses, and secrets (passwords, keys, tokens) behind
a name and a separator. Around every anchor (a digit, a spoken at, a name of a secret) all segments of whole parts compete: a
run of digit groups offers each of its stretches as a phone and as a card, a spoken address each number of parts on both
sides, a secret each place where its value may end. A segment has features of the whole span, of what stands beside it and of
whether it could go on; a segmentation scores the sum of its segments' weights, and text outside of segments scores zero.
Decoding is dynamic programming over segment borders that chooses the best set of segments without overlaps, boundaries and
types together. A segment has at most MAX_SPAN characters and each place starts a bounded number of them, so the work is
linear in the text. Base spans are fixed segments that others must not touch.

Weights are fitted by gradient on the exact log-likelihood (forward and backward sums over the same lattice) of sentences
made by a seeded generator, positives and look-alikes; there is no labelled personal data in the tables.

Defined results: null counts as the empty text, without spans. Repeated rows each get their own row.
"""

from __future__ import annotations

import bisect
import functools
import hashlib
import itertools
import math
import random
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from seqschema.llm.common import append_columns

KINDS = ("email", "ip", "card", "phone")
MAX_SPAN, CONTEXT = 128, 24
QUOTES = ("'", '"')

LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)+")
IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
NOT_DIGIT, DIGIT = re.compile(r"[^0-9]+"), re.compile("[0-9]")

Span = tuple[int, int, str]


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = int(c) << (k & 1)
        total += d - 9 if d > 9 else d
    return total % 10 == 0


def emails(text: str) -> Iterator[Span]:
    """From each @ to both sides: what a leftmost search finds, in linear time."""
    last, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > last and text[start - 1] in LOCAL:
            start -= 1
        m = DOMAIN.match(text, at + 1) if start < at else None
        if m:
            yield start, m.end(), "email"
            last = m.end()
        at = text.find("@", max(last, at + 1))


def base_spans(text: str) -> list[Span]:
    """By kind as listed, then by start."""
    out = list(emails(text))
    for m in IP.finditer(text):
        if all(len(p := x.lstrip("0")) <= 3 and int(p or 0) <= 255 for x in m.group().split(".")):
            out.append((*m.span(), "ip"))
    for m in CARD.finditer(text):
        if m.end() - m.start() >= 16:
            digits = NOT_DIGIT.sub("", m.group())
            if 16 <= len(digits) <= 19 and luhn(digits):
                out.append((*m.span(), "card"))
    for m in PHONE.finditer(text):
        if 8 <= sum(c.isdigit() for c in m.group()) <= 15:
            out.append((*m.span(), "phone"))
    return out


#: Kinds of the model beside the base ones, in the order of the list.
ALL_KINDS = (*KINDS, "secret")
GROUP, GAP = re.compile("[0-9]+"), re.compile(r"[ ().-]{1,2}")
MOST_DIGITS, MOST_GROUPS, MOST_PARTS = 19, 6, 4
#: Spoken marks, and the parts of an address on both sides of the at.
AT = re.compile(r" ?[(\[](?:at|AT)[)\]] ?| at ")
DOT = r"(?: ?[(\[](?:dot|DOT)[)\]] ?| dot |\.)"
RIGHT, LEFT = re.compile(rf"[A-Za-z0-9-]{{1,63}}(?:{DOT}[A-Za-z0-9-]{{1,63}}){{1,{MOST_PARTS}}}"), re.compile(rf"(?:[A-Za-z0-9_%+-]{{1,64}}{DOT}){{0,{MOST_PARTS}}}[A-Za-z0-9_%+-]{{1,64}}\Z")
DOT_AT = re.compile(DOT)
LONG_IP = re.compile(r"(?<![0-9A-Fa-f:])(?:[0-9A-Fa-f]{1,4}:{1,2}){3,7}[0-9A-Fa-f]{1,4}(?![0-9A-Fa-f:])")
NAMED = re.compile(r"(?i:password|passwd|passphrase|secret|token|api[ _-]?key|access[ _-]?key|credential)s?[\"']?(?: ?(?:[:=]|=>|is) ?)([\"']?)")
VALUE, VALUE_END = re.compile(r"[^\s\"'<>]{4,128}"), re.compile(r"[^A-Za-z0-9_-]+")
#: What a text holds, in these cases, if a pattern above matches: tested first, for most texts hold none.
SPOKEN, NAMES = (" at ", "(at)", "[at]", "(AT)", "[AT]", "(at]", "[at)", "(AT]", "[AT)"), ("passw", "passphrase", "secret", "token", "key", "credential")
CUES = {
    "email": ("mail", "contact", "write", "reach", "e-mail"),
    "ip": ("ip", "host", "server", "address", "ipv6"),
    "card": ("card", "visa", "amex", "credit", "pay"),
    "phone": ("phone", "tel", "call", "fax", "mobile", "cell", "dial", "ring"),
    "secret": ("password", "passwd", "secret", "token", "key", "credential"),
}
AGAINST = ("version", "order", "isbn", "invoice", "ref", "no", "id", "serial", "part", "section", "page", "item", "ticket", "case")


def digit_candidates(text: str) -> Iterator[Span]:
    """Stretches of at most MOST_GROUPS neighbouring digit groups, as a phone and as a card."""
    groups = [m.span() for m in GROUP.finditer(text)]
    for i, (start, _) in enumerate(groups):
        if start and (text[start - 1].isalnum() or text[start - 1] == "_"):
            continue
        size = 0
        for j in range(i, min(i + MOST_GROUPS, len(groups))):
            if j > i and not GAP.fullmatch(text, groups[j - 1][1], groups[j][0]):
                break
            size += groups[j][1] - groups[j][0]
            if size > MOST_DIGITS:
                break
            end = groups[j][1]
            for begin in (start, start - 1) if start and text[start - 1] in "(+" else (start,):
                if 7 <= size <= 15:
                    yield begin, end, "phone"
                if size >= 12:
                    yield begin, end, "card"


def spoken_candidates(text: str) -> Iterator[Span]:
    if not any(x in text for x in SPOKEN):
        return
    for at in AT.finditer(text):
        right = RIGHT.match(text, at.end())
        left = LEFT.search(text, max(0, at.start() - MAX_SPAN // 2), at.start())
        if right and left:
            starts = [left.start(), *(m.end() for m in DOT_AT.finditer(text, left.start(), at.start()))]
            ends = [*(m.start() for m in DOT_AT.finditer(text, right.start(), right.end())), right.end()][1:]
            yield from ((a, b, "email") for a in starts for b in ends)


def secret_candidates(text: str) -> Iterator[Span]:
    low = text.lower()
    if not any(x in low for x in NAMES):
        return
    for name in NAMED.finditer(text):
        if value := VALUE.match(text, name.end()):
            ends = [m.start() for m in VALUE_END.finditer(text, value.start() + 1, value.end())][:MOST_PARTS]
            yield from ((value.start(), b, "secret") for b in dict.fromkeys([*ends, value.end()]) if b - value.start() >= 4)


def candidates(text: str) -> list[Span]:
    out = [*spoken_candidates(text), *secret_candidates(text)]
    if DIGIT.search(text):
        out += digit_candidates(text)
    if text.count(":") >= 3:
        out += ((*m.span(), "ip") for m in LONG_IP.finditer(text))
    return [s for s in dict.fromkeys(out) if s[1] - s[0] <= MAX_SPAN]


def features(text: str, span: Span) -> list[str]:
    """Of the whole span: its make-up and shape; of its surroundings: cue words before it, what stands beside it, and
    whether it could go on."""
    start, end, kind = span
    body = text[start:end]
    digits = NOT_DIGIT.sub("", body)
    before = re.split(r"[^a-z0-9-]+", text[max(0, start - CONTEXT) : start].lower())
    left, right = text[start - 1 : start], text[end : end + 1]
    sizes = [len(x) for x in GROUP.findall(body)]
    marks = set(NOT_DIGIT.findall(body)) if kind in ("phone", "card") else set()
    cue, against = any(w.startswith(c) for w in before for c in CUES[kind]), any(w in AGAINST for w in before)
    more_left = bool(re.search(r"[0-9][ ().-]{1,2}\(?\Z", text[max(0, start - 4) : start]))
    more_right = bool(re.match(r"[ ().-]{1,2}[0-9]", text[end : end + 3]))
    out = ["any", f"digits{min(len(digits), 20)}" if kind in ("phone", "card") else f"length{min(end - start, 64) // 8}"]
    if kind in ("phone", "card"):
        out += [f"shape{'-'.join(map(str, sizes[:5]))}", f"marks{len(marks)}"]
    out += [name for name, on in (
        ("cue", cue), ("against", against), ("bare", not cue and not against), ("luhn", len(digits) >= 13 and luhn(digits)), ("open", body[0] == "("), ("plus", body[0] == "+"), ("unopened", left == "(" or ")" in body and "(" not in body),
        ("spoken", " dot " in body or "(dot)" in body or "[dot]" in body), ("plain_at", " at " in body), ("colons", body.count(":") == 7), ("joined", digits == body),
        ("edge", left.isalnum() or right.isalnum() or left in ("_", "-") and left != ""), ("more_left", more_left), ("more_right", more_right), ("more_dot", kind == "email" and bool(DOT_AT.match(text, end))),
        ("quoted", left in ("'", '"') and left != "" and left == right), ("mixed", bool(digits) and any(c.isalpha() for c in body)), ("hex", len(body) >= 16 and all(c in "0123456789abcdefABCDEF" for c in body)),
        ("word", body.isalpha()), ("inner", VALUE_END.search(body) is not None), ("last", not right or right.isspace() or right in "\"',;.!?)#*$%&|"), ("said", text[max(0, start - 4) : start].strip().endswith("is")),
    ) if on]
    return [f"{kind}:{x}" for x in out]


def lattice(spans: list[Span]) -> tuple[list[int], dict[int, int], list[list[int]], list[list[int]]]:
    """Borders in order, their places, and the spans that end and start at each."""
    borders = sorted({0, *(x for s in spans for x in s[:2])})
    place = {b: i for i, b in enumerate(borders)}
    ends: list[list[int]] = [[] for _ in borders]
    starts: list[list[int]] = [[] for _ in borders]
    for k, s in enumerate(spans):
        starts[place[s[0]]].append(k)
        ends[place[s[1]]].append(k)
    return borders, place, ends, starts


def decode(spans: list[Span], scores: list[float]) -> list[Span]:
    """The best set of spans without overlaps: best score up to each span border, with the span that ends there."""
    borders, place, ends, _ = lattice(spans)
    best = [(0.0, -1)] * len(borders)
    for i in range(1, len(borders)):
        best[i] = max([(best[i - 1][0], -1), *((best[place[spans[k][0]]][0] + scores[k], k) for k in ends[i])], key=lambda x: x[0])
    out, at = [], len(borders) - 1
    while at > 0:
        k = best[at][1]
        if k >= 0:
            out.append(spans[k])
            at = place[spans[k][0]]
        else:
            at -= 1
    return out[::-1]


def marginals(spans: list[Span], scores: list[float]) -> list[float]:
    """The probability of each span under the model: forward and backward sums over the lattice of borders."""
    borders, place, ends, starts = lattice(spans)
    fore, back = [0.0] * len(borders), [0.0] * len(borders)

    def log_add(values: list[float]) -> float:
        top = max(values)
        return top + math.log(sum(math.exp(v - top) for v in values))

    for i in range(1, len(borders)):
        fore[i] = log_add([fore[i - 1], *(fore[place[spans[k][0]]] + scores[k] for k in ends[i])])
    for i in range(len(borders) - 2, -1, -1):
        back[i] = log_add([back[i + 1], *(back[place[spans[k][1]]] + scores[k] for k in starts[i])])
    return [math.exp(fore[place[s[0]]] + w + back[place[s[1]]] - fore[-1]) for s, w in zip(spans, scores, strict=True)]


def examples(seed: int, number: int) -> list[tuple[str, set[Span]]]:
    """Made-up sentences with the spans that count as personal data, and look-alikes that do not."""
    rnd = random.Random(seed)
    some = lambda n: "".join(rnd.choice("0123456789") for _ in range(n))
    word = lambda: "".join(rnd.choice("aeinorstlhd") for _ in range(rnd.randrange(3, 9)))

    def amex() -> str:
        head = "3" + rnd.choice("47") + some(12)
        return next(head + str(k) for k in range(10) if luhn(head + str(k)))

    def made() -> tuple[str, str, str]:
        spoken = rnd.choice([(" at ", " dot "), ("(at)", "(dot)"), (" [at] ", " [dot] ")])
        sep = rnd.choice("-. ")
        return rnd.choice([
            ("email", rnd.choice(["mail ", "contact ", "reach me: ", ""]), f"{word()}.{word()}{spoken[0]}{word()}{spoken[1]}com"),
            ("phone", rnd.choice(["call ", "phone: ", "tel ", "mobile "]), f"{some(3)}{sep}{some(3)}{sep}{some(4)}"),
            ("phone", rnd.choice(["call ", "dial ", ""]), f"({some(3)}) {some(3)}-{some(4)}"),
            ("card", rnd.choice(["amex ", "card ", "pay with "]), amex()),
            ("ip", rnd.choice(["server ", "ipv6 ", ""]), ":".join(f"{rnd.randrange(65536):x}" for _ in range(8))),
            ("", rnd.choice(["order ", "ref ", "invoice ", "serial ", "item "]), f"{some(3)}{sep}{some(3)}{sep}{some(4)}"),
            ("", rnd.choice(["part ", "id ", ""]), f"3{some(14)}"),
            ("", "", f"{word()} at {word()}.{word()}"),
            ("", rnd.choice(["section ", "version ", ""]), f"{some(3)}.{some(3)}.{some(4)}"),
            ("phone", rnd.choice(["call ", "fax ", "cell ", "tel "]), f"{some(2)}{sep}{some(rnd.choice([3, 4]))}{sep}{some(4)}"),
            ("phone", rnd.choice(["call ", "phone ", ""]), f"({some(3)}) {some(3)} {some(4)}"),
            ("email", rnd.choice(["mail ", ""]), f"{word()}{spoken[0]}{word()}{spoken[1]}co{spoken[1]}uk"),
            ("", "", f"{some(1)} {some(2)} {some(1)} {some(2)} {some(3)}"),
            ("", rnd.choice(["case ", "ticket "]), some(rnd.randrange(7, 14))),
            ("", "", rnd.choice(["the secret is out", "a token of thanks", "the password is wrong", "tokens: many words", "secret: nobody knows"])),
            secret(), secret(), secret(),
        ])

    def secret() -> tuple[str, str, str]:
        name = rnd.choice(["password", "token", "api_key", "secret", "API key", "access_key", "passwd"])
        value = rnd.choice(["".join(rnd.choice("0123456789abcdef") for _ in range(rnd.choice([24, 32, 40]))), f"{word()}{some(3)}", f"{word().title()}-{some(4)}", "".join(rnd.choice("abcXYZ0189_") for _ in range(20))])
        return "secret", f"{name}{rnd.choice([' = ', '=', ': ', ':'])}" + rnd.choice(['"', "'", ""]), value

    out = []
    for _ in range(number):
        text, gold = "", set()
        for _ in range(rnd.randrange(1, 4)):
            kind, lead, body = made()
            text += f"{word()} {word()} {lead}"
            if kind:
                gold.add((len(text), len(text) + len(body), kind))
            text += f"{body}{lead[-1:] if lead[-1:] in QUOTES else ''}{rnd.choice(['', '', '.', ',', '!!'])} {word()}. "
        out.append((text, gold))
    return out


@functools.lru_cache(maxsize=2)
def fit(seed: int = 5, number: int = 400, rounds: int = 12, step: float = 0.3, decay: float = 1e-3) -> dict[str, float]:
    """Weights by stochastic gradient on the log-likelihood."""
    weights: dict[str, float] = {}
    prepared = []
    for text, gold in examples(seed, number):
        spans = candidates(text)
        prepared.append((spans, [features(text, s) for s in spans], [s in gold for s in spans]))
    for r in range(rounds):
        for spans, feats, right in prepared:
            scores = [sum(weights.get(f, 0.0) for f in fs) for fs in feats]
            for p, fs, y in zip(marginals(spans, scores), feats, right, strict=True):
                for f in fs:
                    w = weights.get(f, 0.0)
                    weights[f] = w + step / (1 + r) * ((1.0 if y else 0.0) - p - decay * w)
    return weights


def added_spans(text: str, base: list[Span], weights: dict[str, float]) -> list[Span]:
    """The model's spans beside the base ones."""
    spans = candidates(text)
    if base and spans:
        # of all base spans that start before a candidate ends, does one end behind its start
        fixed = sorted(s[:2] for s in base)
        starts, reach = [a for a, _ in fixed], list(itertools.accumulate((b for _, b in fixed), max))
        spans = [s for s in spans if not (k := bisect.bisect_left(starts, s[1])) or reach[k - 1] <= s[0]]
    if not spans:
        return []
    return decode(spans, [sum(weights.get(f, 0.0) for f in features(text, s)) for s in spans])


def listed(spans: list[Span]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in sorted(spans, key=lambda s: (ALL_KINDS.index(s[2]), s[0], s[1])))


def find_personal_data(docs: DataFrame, text_col: str = "text", keep=("doc_id",)) -> DataFrame:
    """Counts of the base spans by kind, the digest of their list, and the list of all spans."""
    weights = fit()

    def kernel():
        def work(texts, _):
            rows = []
            for text in texts:
                base = base_spans(text)
                counts = [sum(s[2] == k for s in base) for k in KINDS]
                rows.append((*counts, hashlib.sha256(listed(base).encode()).hexdigest(), listed(base + added_spans(text, base, weights))))
            kinds = [pa.int64()] * 4 + [pa.string()] * 2
            return [pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)]

        return work

    fields = [(f"n_{k}", T.LongType()) for k in KINDS] + [("base_sha256", T.StringType()), ("spans", T.StringType())]
    return append_columns(docs, text_col, kernel, fields, list(keep))
