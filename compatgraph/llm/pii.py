"""Personal data: fixed base patterns, and candidate gradient boosting for what they miss.

Base spans (email, ip, card, phone) follow fixed patterns and always stay.  High-recall generators propose further,
overlapping spans: written-out emails, addresses of a host without a dot, numbers in groups, IPv6 addresses (compressed ones too), account
numbers, dates.  Boosted trees score each by its format and the words around it: a date is proposed wherever it stands and reported after
words of birth.  A logistic curve through held-out margins calibrates the scores, and each kind has the
threshold at which held-out precision reaches ``PRECISION``.  Of overlapping candidates the best score stays.

There are no labelled spans, so the trees are fitted on ``EXAMPLES`` generated examples (a seeded rule below), a bound that does
not depend on the input.  Fit, calibration and thresholds use three families of examples that share neither formats nor announcing
words, each with formats that are personal data in one context and not in another.  Offsets are in code points.  Null and empty texts have
no spans; each row is read on its own, so repeated rows get equal results; an empty table gives an empty result.  Every
pattern is linear in the text or bounded in length, so very long texts are read whole; other columns, whatever their names, are not read.
"""

from __future__ import annotations

import hashlib
import ipaddress
import random
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import boosting
from .common import col, map_text, narrow, texts

EXAMPLES, PRECISION, SEED = 15_000, 0.95, 7
BASE = ("email", "ip", "card", "phone")
KINDS = (*BASE, "wordmail", "hostmail", "number", "ipv6", "iban", "birth")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
DIGIT = re.compile("[0-9]")
WORDMAIL = re.compile(r"[A-Za-z0-9._%+-]{1,64}\x20?(?:\(at\)|\[at\]|\{at\}|\x20at\x20)\x20?[A-Za-z0-9-]{1,63}(?:\x20?(?:\(dot\)|\[dot\]|\{dot\}|\x20dot\x20|\.)\x20?[A-Za-z]{2,12}){1,4}", re.I)
NUMBER = re.compile(r"(?<![A-Za-z0-9.+(/-])\(?[0-9](?:[\x20().\-/]{0,2}[0-9]){5,18}(?![A-Za-z0-9])")
IPV6 = re.compile(r"(?<![0-9A-Za-z:.])(?:[0-9A-Fa-f]{0,4}:){2,7}[0-9A-Fa-f]{0,4}(?![0-9A-Za-z:])")
HOST = re.compile(r"[A-Za-z0-9-]{2,63}+(?![A-Za-z0-9-]|\.[A-Za-z0-9-])")
DATE = re.compile(r"(?<![0-9./-])(?:[0-9]{1,2}([./-])[0-9]{1,2}\1(?:19|20)[0-9]{2}|(?:19|20)[0-9]{2}-[0-9]{2}-[0-9]{2})(?![0-9]|[./-][0-9])")
IBAN = re.compile(r"(?<![A-Z0-9])[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]{4}){2,7}(?:\x20?[A-Z0-9]{1,3})?(?![A-Z0-9])")
# Words that announce personal data, and words that announce other numbers.
NEAR = {
    "phone": "phone tel call mobile fax cell whatsapp telefon appel móvil dial reach".split(),
    "id": "ssn social security passport id ausweis dni taxpayer licence".split(),
    "bank": "iban account bank konto compte cuenta transfer deposit payee".split(),
    "mail": "email mail contact write e-mail correo inbox message send".split(),
    "host": "ip address host login client visitor session peer connected".split(),
    "birth": "born birthday birth dob geboren né nacido geburtstag nacimiento".split(),
    "other": "isbn version order invoice ref item page serial part model released total price lot published updated".split(),
}


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def _digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def emails(text: str) -> list[tuple[int, int]]:
    """Leftmost matches, from each @: the local part is the run before it, the domain the match after it."""
    out, last, at = [], 0, text.find("@")
    while at >= 0:
        a = at
        while a > last and text[a - 1] in LOCAL:
            a -= 1
        m = DOMAIN.match(text, at + 1) if a < at else None
        if m:
            out.append((a, m.end()))
            last = m.end()
        else:
            last = max(last, at + 1)  # no match has this @ in it
        at = text.find("@", max(last, at + 1))
    return out


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """The base spans as (start, end, kind), by start and then kind as listed."""
    found = [(a, b, "email") for a, b in emails(text)] if "@" in text else []
    if DIGIT.search(text):
        if "." in text:
            found += [(*m.span(), "ip") for m in IP.finditer(text) if all(len(p) < 4 or not p.lstrip("0")[3:] for p in m[0].split(".")) and all(int(p.lstrip("0")[:4] or 0) <= 255 for p in m[0].split("."))]
        for m in CARD.finditer(text):
            if 12 <= m.end() - m.start() <= 37 and 12 <= len(d := _digits(m[0])) <= 19 and luhn(d):
                found.append((*m.span(), "card"))
        if "+" in text:
            found += [(*m.span(), "phone") for m in PHONE.finditer(text) if 9 <= len(_digits(m[0])) <= 15]
    return sorted(found, key=lambda s: (s[0], KINDS.index(s[2])))


def _ipv6(s: str) -> bool:
    try:
        return bool(ipaddress.IPv6Address(s))
    except ValueError:
        return False


def candidates(text: str) -> list[tuple[int, int, str]]:
    """Spans that may be personal data, overlapping as they come."""
    out = []
    low = text.lower()
    if any(x in low for x in ("(at)", "[at]", "{at}", " dot ")):
        out += [(*m.span(), "wordmail") for m in WORDMAIL.finditer(text)]
    at, last = text.find("@"), 0
    while at >= 0:
        a = at
        while a > max(last, at - 64) and text[a - 1] in LOCAL:
            a -= 1
        m = HOST.match(text, at + 1) if a < at else None
        if m:
            out.append((a, m.end(), "hostmail"))
        last = at + 1
        at = text.find("@", last)
    if DIGIT.search(text):
        out += [(*m.span(), "number") for m in NUMBER.finditer(text)]
        out += [(*m.span(), "iban") for m in IBAN.finditer(text)]
        out += [(*m.span(), "birth") for m in DATE.finditer(text)]
    if text.count(":") > 1:
        out += [(*m.span(), "ipv6") for m in IPV6.finditer(text) if len(m[0]) > 2 and _ipv6(m[0])]
    return out


def describe(text: str, a: int, b: int, kind: str) -> list[float]:
    """Format and context of a candidate."""
    s, before, after = text[a:b], text[max(0, a - 60) : a].lower(), text[b : b + 30].lower()
    d = _digits(s)
    groups = [len(g) for g in re.findall("[0-9]+", s)]
    words = re.findall(r"[^\W_][\w-]*", before)[-5:][::-1]
    follow = re.findall(r"[^\W_][\w-]*", after)[:2]
    # how near the closest announcing word of each group stands before, and whether one follows
    near = [float(next((5 - i for i, v in enumerate(words) if v in of or v.rstrip("s") in of), 0)) for of in NEAR.values()]
    behind = float(any(v in of for of in list(NEAR.values())[:-1] for v in follow))
    iban = 0.0
    if kind == "iban":
        flat = s.replace(" ", "")
        iban = float(int("".join(str(int(c, 36)) for c in flat[4:] + flat[:4])) % 97 == 1)
    spelled = "at" in s.lower() and ("(" in s or "[" in s or "{" in s or "dot" in s.lower())
    return [
        float(KINDS.index(kind)), float(b - a), float(len(d)), float(len(groups)), float(max(groups, default=0)), float(groups[0] if groups else 0), float(groups[-1] if groups else 0),
        float("(" in s), float("." in s), float("/" in s), float("-" in s), float(" " in s), float(s[:1] == "0"), iban, float(bool(d)), float(s.count(":")), float(spelled), *near, behind,
    ]


def examples(family: int, n: int = EXAMPLES // 3, seed: int = SEED) -> tuple[np.ndarray, np.ndarray, list[str]]:
    """Generated candidates of one of three families, with labels.

    A format has the odds of being personal data where nothing announces it; an announcing word raises them, a word that announces
    other numbers lowers them.  Formats and words are dealt to the families in turn, so no family has another's.
    """
    r = random.Random(seed + family)
    num = lambda k: "".join(r.choice("0123456789") for _ in range(k))
    word = lambda: "".join(r.choice("aeiourstlnmdp") for _ in range(r.randint(2, 9)))
    hexed = lambda k, top=65536: [f"{r.randrange(1, top):x}" for _ in range(k)]
    day, month, year = (lambda: r.randint(10, 28)), (lambda: r.randint(10, 12)), (lambda: r.randint(1930, 2024))
    end = lambda: r.choice(["com", "org", "net", "de", "es"])

    def account(gap: bool, lands: list[str]) -> str:
        body, land = num(18), r.choice(lands)
        flat = body + "".join(str(int(c, 36)) for c in land) + "00"
        out = land + f"{98 - int(flat) % 97:02d}" + body
        return " ".join(re.findall("....?", out)) if gap else out

    def spoiled(s: str) -> str:
        """An account number whose check digits are wrong."""
        return s[:-1] + str((int(s[-1]) + r.randint(1, 9)) % 10)

    formats = {
        "phone": (0.75, [
            lambda: f"({num(3)}) {num(3)}-{num(4)}", lambda: f"{num(3)}.{num(3)}.{num(4)}", lambda: f"{num(3)} {num(3)} {num(4)}",
            lambda: f"{num(3)}-{num(3)}-{num(4)}", lambda: f"0{num(3)}/{num(7)}", lambda: f"0{num(1)} {num(2)} {num(2)} {num(2)} {num(2)}",
            lambda: f"(0{num(2)}) {num(4)} {num(4)}", lambda: f"0{num(3)}-{num(6)}", lambda: f"({num(3)}) {num(7)}",
        ]),
        "id": (0.2, [lambda: f"{num(3)}-{num(2)}-{num(4)}", lambda: f"{num(3)} {num(2)} {num(4)}", lambda: f"{num(2)}-{num(7)}-{num(1)}", lambda: num(9), lambda: num(10), lambda: num(8)]),
        "bank": (0.95, [lambda: account(r.random() < 0.5, ["DE", "NL"]), lambda: account(r.random() < 0.5, ["FR", "IT"]), lambda: account(r.random() < 0.5, ["ES", "GB"])]),
        "mail": (0.95, [
            lambda: f"{word()} (at) {word()}.{end()}", lambda: f"{word()} [at] {word()} [dot] {end()}", lambda: f"{word()} at {word()} dot {end()}",
            lambda: f"{word()}{{at}}{word()}.{end()}", lambda: f"{word()} (at) {word()} (dot) {end()}", lambda: f"{word()}(at){word()} dot {end()}",
        ]),
        "host": (0.9, [
            lambda: ":".join(hexed(8)), lambda: ":".join(hexed(8)).upper(), lambda: ":".join(x.zfill(4) for x in hexed(8)),
            lambda: ":".join(hexed(3)) + "::" + hexed(1)[0], lambda: "2001:db8:" + ":".join(hexed(2)) + "::" + hexed(1)[0], lambda: ":".join(hexed(2)) + "::" + ":".join(hexed(3)),
            lambda: "fe80::" + hexed(1)[0], lambda: "::" + ":".join(hexed(2)), lambda: "fd00::" + ":".join(hexed(r.randint(1, 3))),
        ]),
        "birth": (0.02, [lambda: f"{day()}/{month()}/{year()}", lambda: f"{year()}-{month()}-{day()}", lambda: f"{day()}.{month()}.{year()}", lambda: f"{day()}-{month()}-{year()}", lambda: f"{r.randint(1, 9)}.{month()}.{year()}", lambda: f"{month()}/{day()}/{year()}"]),
        "inbox": (0.5, [lambda: f"{word()}@localhost", lambda: f"{word()}.{word()}@mail{num(1)}", lambda: f"{word()}{num(2)}@{word()}", lambda: f"{word()}@{word()}-{word()}", lambda: f"{word()}_{word()}@intranet", lambda: f"{word()}+{word()}@server"]),
        "other": (0.0, [
            lambda: num(16), lambda: num(14), lambda: num(17),
            lambda: f"{r.randint(1, 9)}.{num(3)}.{num(3)}", lambda: f"{num(3)}.{num(2)}.{num(3)}.{num(2)}", lambda: f"97{r.choice('89')}-{num(1)}-{num(4)}-{num(4)}-{num(1)}",
            lambda: spoiled(account(r.random() < 0.5, ["DE", "NL"])), lambda: spoiled(account(r.random() < 0.5, ["FR", "IT"])), lambda: spoiled(account(r.random() < 0.5, ["ES", "GB"])),
            lambda: f"{r.choice(['be', 'ad'])}::{r.choice(['de', 'c'])}", lambda: f"{r.choice(['fa', 'cab'])}::{r.choice(['ace', 'f'])}", lambda: f"{r.choice(['dad', 'e'])}::{r.choice(['bee', 'bad'])}",
            lambda: word() + " at " + word() + "." + word()[:8], lambda: word() + " at the " + word() + " dot " + word(), lambda: word() + " at " + word() + ". " + word()[:8],
            lambda: " ".join(num(r.randint(1, 4)) for _ in range(r.randint(3, 6))), lambda: f"{num(4)} {num(4)}", lambda: f"{year()}-{year()}",
            lambda: f"{word()}@{r.choice('12')}", lambda: f"{num(2)}@{num(3)}", lambda: f"{word()}@{num(2)}x",
        ]),
    }
    announced = {"inbox": "mail"}
    mine = {g: (p, f[family::3]) for g, (p, f) in formats.items()}
    said = {g: v[family::3] for g, v in NEAR.items()}
    x, y, kinds = [], [], []
    while len(x) < n:
        group = "other" if r.random() < 0.3 else r.choice(list(mine)[:-1])
        odds, makers = mine[group]
        context = r.random()
        if context < 0.4:
            lead, odds = r.choice(said[announced.get(group, group)]), max(odds, 0.97) if group != "other" else 0.0
        elif context < 0.65:
            lead, odds = r.choice(said["other"]), odds * (0.9 if group in ("bank", "host") else 0.05)  # a right check sum, or the form of an address, says more than a word
        elif context < 0.75:
            lead = r.choice(said[r.choice([g for g in said if g not in (group, announced.get(group), "other")])])
            odds = odds if group in ("bank", "mail", "host") else odds * 0.3  # announced as something else
        else:
            lead = word()
        label = r.random() < odds
        head = f"{word()} {word()} {lead}{r.choice([':', '', '', ' ' + word(), ' no'])} "
        text = head + r.choice(makers)() + f" {word()} {word()}"
        for a, b, kind in candidates(text):
            if b > len(head):
                x.append(describe(text, a, b, kind)), y.append(float(label)), kinds.append(kind)
    return np.array(x), np.array(y), kinds


_MODEL: dict = {}


def model() -> dict:
    """Trees, calibration curve and thresholds, each from a family of its own; the same at every call."""
    if not _MODEL:
        x, y, _ = examples(0)
        m = boosting.fit(x, y, rounds=80, depth=4, rate=0.2)
        x, y, _ = examples(1)
        m["curve"] = boosting.calibrate(boosting.margin(m, x), y)
        x, y, kinds = examples(2)
        p, thresholds, reached = boosting.probability(m, x), {}, {}
        for kind in KINDS[4:]:
            own = [i for i, k in enumerate(kinds) if k == kind]
            q, t = p[own], y[own]
            # the least threshold from which on precision holds
            ok = [c for c in np.unique(np.floor(q * 1000) / 1000) if c >= 0.5 and t[q >= c].mean() >= PRECISION] if own else []
            thresholds[kind] = float(min(ok)) if ok else 2.0
            reached[kind] = (float(t[q >= thresholds[kind]].mean()) if ok else 0.0, float((t * (q >= thresholds[kind])).sum() / max(1, t.sum())))
        m["thresholds"], m["reached"] = thresholds, reached
        _MODEL.update(m)
    return _MODEL


def all_spans(text: str, m: dict, base: list[tuple[int, int, str]]) -> list[tuple[int, int, str]]:
    """Base spans and the candidates above their kind's threshold, the best of those that overlap."""
    found = [(a, b, k) for a, b, k in candidates(text) if not any(a < y and x < b for x, y, _ in base)]
    if not found:
        return base
    p = boosting.probability(m, np.array([describe(text, *c) for c in found]))
    added: list[tuple[int, int, str]] = []
    for q, (a, b, k) in sorted(zip(-p, found, strict=True)):
        if -q >= m["thresholds"][k] and not any(a < y and x < b for x, y, _ in added):
            added.append((a, b, k))
    return sorted(base + added, key=lambda s: (s[0], KINDS.index(s[2])))


def written(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in spans)


def redact(text: str, spans: list[tuple[int, int, str]]) -> str:
    out, at = [], 0
    for a, b, k in spans:
        if a >= at:
            out += [text[at:a], f"<{k}>"]
            at = b
    return "".join(out) + text[at:]


def find(docs: DataFrame, *, with_text: bool = False) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, [redacted] of every document."""
    m = dict(model())

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        rows = []
        for t in texts(batch):
            base = base_spans(t)
            spans = all_spans(t, m, base)
            rows.append((*[sum(s[2] == k for s in base) for k in BASE], hashlib.sha256(written(base).encode()).hexdigest(), written(spans), *([redact(t, spans)] if with_text else [])))
        arrays = [pa.array(x, t) for x, t in zip(zip(*rows, strict=True), [pa.int64()] * 4 + [pa.string()] * 3, strict=False)]
        return pa.RecordBatch.from_arrays([col(batch, "doc_id"), *arrays], names=["doc_id", *[f"n_{k}" for k in BASE], "base_sha256", "spans", "redacted"][: 1 + len(arrays)])

    return map_text(narrow(docs, "doc_id", "text"), run, "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string" + ", redacted string" * with_text)
