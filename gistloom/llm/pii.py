"""Personal data: candidate spans, boosted trees, calibrated thresholds.

*Base patterns* (e-mail, IP, card, phone) are found exactly and always kept.  *Generators* propose
further spans with high recall: secrets after a cue, access keys, long hex keys, national phone
numbers, social security numbers, bank accounts, spelled-out e-mail addresses, tokens with a
provider's prefix, bearer and web tokens, private key blocks.  Boosted trees score
every proposal from its format and its context; each kind has its own threshold, the lowest at which
precision reaches ``precision`` on a part of the training cases; a kind that never gets there keeps
one half.  Of accepted proposals that overlap, the best stays; none may overlap a base span.

There is no table of labelled spans, so the trees learn from cases made by rule, with a fixed seed:
true values in typical contexts and look-alikes, many of the same shape in other contexts (commit
hashes, part numbers, placeholders, tickets).  Defined cases: a null or empty text has no spans; texts are searched whole, in linear
time, whatever their length; repeated rows are searched alike; an empty table gives an empty result.
Offsets are code points, end exclusive.
"""

from __future__ import annotations

import bisect
import hashlib
import math
import random
import re
from collections import Counter
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gistloom.llm import trees

BASE = ("email", "ip", "card", "phone")
# The patterns of the base kinds.  Look-behinds and the split at "@" only avoid quadratic time.
DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"(?<![0-9])([0-9]+)\.([0-9]+)\.([0-9]+)\.([0-9]+)")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
DIGIT = re.compile(r"[0-9]")

GENERATORS = {
    "secret": re.compile(r"(?i)\b(?:api[_-]?key|apikey|secret|token|passw(?:or)?d|pwd|auth)[\"']?(?:\s{0,3}[=:]\s{0,3}|\s{1,3}is\s{1,3})[\"']?([A-Za-z0-9/+_\-]{6,})"),
    "access_key": re.compile(r"(?<![A-Za-z0-9])([A-Z]{3,5}[A-Z0-9]{14,20})(?![A-Za-z0-9])"),
    "hex_key": re.compile(r"(?<![A-Za-z0-9])([0-9a-f]{24,})(?![A-Za-z0-9])"),
    "national_phone": re.compile(r"(?<![0-9+.-])(\(?[0-9]{3}\)?[ .-][0-9]{3}[ .-][0-9]{4})(?![0-9])"),
    "ssn": re.compile(r"(?<![0-9-])([0-9]{3}-[0-9]{2}-[0-9]{4})(?![0-9-])"),
    "iban": re.compile(r"(?<![A-Za-z0-9])([A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?)(?![A-Za-z0-9])"),
    "spelled_email": re.compile(r"(?i)(?<![a-z0-9])([a-z0-9._]{2,40} ?[\[(] ?at ?[\])] ?[a-z0-9-]{2,40} ?[\[(] ?dot ?[\])] ?[a-z]{2,10})"),
    "prefixed_token": re.compile(r"(?<![A-Za-z0-9])((?:[spr]k_(?:live|test)_|gh[pousr]_|xox[abprs]-|AIza|glpat-)[A-Za-z0-9_-]{10,})"),
    "bearer": re.compile(r"(?i)\bbearer\s{1,3}([A-Za-z0-9._~+/=-]{12,})"),
    "web_token": re.compile(r"(?<![A-Za-z0-9])(eyJ[A-Za-z0-9_-]{6,}\.[A-Za-z0-9_-]{6,}\.[A-Za-z0-9_-]+)"),
    "private_key": re.compile(r"(-----BEGIN [A-Z ]{0,30}PRIVATE KEY-----[^-]*(?:-----END [A-Z ]{0,30}PRIVATE KEY-----)?)"),
}
# What a text must hold for a generator to find anything: exact cues, so none depends on another's.
CUED = {
    "secret": ("key", "secret", "token", "passw", "pwd", "auth"), "spelled_email": ("dot",), "bearer": ("bearer",),  # in lower case
    "prefixed_token": ("k_live_", "k_test_", "ghp_", "gho_", "ghu_", "ghs_", "ghr_", "xox", "AIza", "glpat-"), "web_token": ("eyJ",), "private_key": ("-----BEGIN ",),
}
LOWERED = ("secret", "spelled_email", "bearer")
DIGITS = ("hex_key", "national_phone", "ssn", "iban")  # kinds that hold a digit; letters alone are no hex key
ADDED = tuple(GENERATORS)
KINDS = BASE + ADDED
IBAN = KINDS.index("iban")
CUES = (
    "key", "secret", "token", "passw", "pwd", "auth", "phone", "call", "tel", "ssn", "social", "iban", "account", "bank", "mail", "contact", "version", "date", "part", "order", "id", "no.",
    "commit", "sha", "hash", "checksum", "ticket", "serial", "example", "build", "md5",
)


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = 2 * d - 9 * (d > 4)
        total += d
    return total % 10 == 0


def mod97(account: str) -> int:
    """Remainder of an international account number with its head moved to the end, letters as 10 to 35; 1 when it is valid."""
    plain = account.replace(" ", "")
    return int("".join(str(int(c, 36)) for c in plain[4:] + plain[:4])) % 97


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of the base kinds, sorted."""
    out = []
    at, used = text.find("@"), 0
    while at >= 0:
        low = at
        while low > used and (text[low - 1].isascii() and (text[low - 1].isalnum() or text[low - 1] in "._%+-")):
            low -= 1
        nxt = at + 1
        if low < at and (m := DOMAIN.match(text, at + 1)):
            out.append((low, 0, m.end()))
            used = nxt = m.end()
        at = text.find("@", nxt)
    if DIGIT.search(text):
        for m in IP.finditer(text):
            if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m.groups()):
                out.append((m.start(), 1, m.end()))
        for m in CARD.finditer(text):
            if m.end() - m.start() >= 12:
                d = m.group().replace(" ", "").replace("-", "")
                if 12 <= len(d) <= 19 and luhn(d):
                    out.append((m.start(), 2, m.end()))
        if "+" in text:
            for m in PHONE.finditer(text):
                if 9 <= sum(c.isdigit() for c in m.group()) <= 15:
                    out.append((m.start(), 3, m.end()))
    return sorted(out)


def proposals(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of all generators; spans may overlap."""
    out, low, digit = [], text.lower(), DIGIT.search(text) is not None
    for k, (kind, pattern) in enumerate(GENERATORS.items(), len(BASE)):
        if kind in DIGITS and not digit:
            continue
        if kind in CUED and not any(c in (low if kind in LOWERED else text) for c in CUED[kind]):
            continue
        out += [(m.start(1), k, m.end(1)) for m in pattern.finditer(text) if kind != "hex_key" or DIGIT.search(m.group(1))]
    return out


def features(text: str, start: int, kind: int, end: int) -> list[float]:
    span, before, after = text[start:end], text[max(0, start - 40) : start], text[end : end + 12]
    n = max(1, len(span))
    digits, upper, lower = sum(c.isdigit() for c in span), sum(c.isupper() for c in span), sum(c.islower() for c in span)
    counts = Counter(span)
    entropy = -sum(c / n * math.log2(c / n) for c in counts.values())
    cues, near = before.lower(), before[-16:].lower()
    flips = sum(a.isdigit() != b.isdigit() for a, b in zip(span, span[1:], strict=False))
    vowels = sum(c in "aeiouAEIOU" for c in span)
    return [
        *[float(kind == k) for k in range(len(BASE), len(KINDS))], n, digits / n, upper / n, lower / n, entropy, len(counts) / n, flips / n, vowels / n,
        float(span.startswith(("AKIA", "ASIA"))), float("[" in span), float(kind == IBAN and mod97(span) == 1), float(span.lower().endswith(("com", "org", "net"))), float(span[0].isalnum()), float(before[-1:].isalnum()), float(after[:1].isalnum()), float(before[-1:] in "\"'=:"), float("=" in before[-4:] or ":" in before[-4:]),
        float(digits > 11 and luhn("".join(c for c in span if c.isdigit() and c.isascii()))), *[float(c in cues) + float(c in near) for c in CUES],
    ]


def _case(rng: random.Random) -> tuple[str, int]:
    """A made-up text with one typical value (1) or look-alike (0)."""
    digits = lambda n: "".join(rng.choice("0123456789") for _ in range(n))
    letters = lambda n, a: "".join(rng.choice(a) for _ in range(n))
    up, hexa, word = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789abcdef", lambda: letters(rng.randint(2, 9), "aeioulnrst")
    plain = lambda most: " ".join(word() for _ in range(rng.randint(0, most)))
    # a cue of another kind further away says nothing
    fill = lambda: f"{rng.choice(CUES)} {word()} {word()} {word()}" if rng.random() < 0.4 else plain(8)
    both = up + up.lower() + "0123456789"
    cue = lambda *c: rng.choice(c)
    phone = lambda: rng.choice(["({}) {}-{}", "{}-{}-{}", "{}.{}.{}", "{} {} {}"]).format(digits(3), digits(3), digits(4))
    blocks = lambda: letters(2, up) + digits(2) + "".join(" " + digits(4) for _ in range(4))
    account = lambda land, rest: f"{land}{98 - mod97(land + '00' + rest):02d}{rest}"
    good = [
        lambda: cue("token = ", "api_key=", "password=", "secret: ", "pwd=", "auth: ", "password is ") + cue("", '"') + letters(rng.randint(12, 64), hexa),
        lambda: cue("password: ", "secret=", "token=", "passwd is ", "pwd: ") + letters(rng.randint(8, 40), both),
        lambda: cue("password: ", "pwd=", "password is ") + word() + digits(rng.randint(2, 5)) + letters(rng.randint(1, 4), both),
        lambda: cue("", "key ", "id ") + cue("AKIA", "ASIA") + letters(16, up + "234567"),
        lambda: cue("", "key ", "token ", "secret ") + letters(rng.choice([32, 40, 64]), hexa),
        lambda: cue("call ", "phone ", "tel ", "contact ", "") + phone(),
        lambda: cue("ssn ", "social security ", "") + f"{digits(3)}-{digits(2)}-{digits(4)}",
        lambda: cue("iban ", "account ", "bank ", "") + account(cue("DE", "FR", "ES", "GB"), "".join(" " + digits(4) for _ in range(4))),
        lambda: cue("mail ", "contact ", "") + f"{word()} [at] {word()} [dot] com",
        lambda: cue("", "key ", "token ") + cue("sk_live_", "ghp_", "gho_", "xoxb-", "AIza", "glpat-", "sk_test_") + letters(rng.randint(16, 40), both),
        lambda: "Authorization: Bearer " + letters(rng.randint(20, 60), both),
        lambda: cue("", "token ") + "eyJ" + letters(18, both) + "." + letters(30, both) + "." + letters(20, both),
        lambda: "-----BEGIN RSA PRIVATE KEY-----\n" + letters(120, both) + "\n-----END RSA PRIVATE KEY-----",
    ]
    bad = [
        lambda: cue("token: ", "secret: ", "password: ", "password is ", "the key is ") + word() + word(),
        lambda: cue("the secret = ", "auth: ", "password is ", "token: ") + cue("required", "none", "disabled", "unknown", "optional", "basic", "forgotten", "changeme", "xxxxxxxx"),
        lambda: cue("token: ", "auth: ") + word() + cue("", "_", "-") + word() + cue("", digits(1)),
        lambda: letters(rng.randint(18, 24), up),
        lambda: "VERSION" + letters(12, up) + digits(1),
        lambda: letters(rng.choice([24, 28]), "ab") if rng.random() < 0.5 else rng.choice("0123456789") * rng.randint(24, 40),
        lambda: cue("commit ", "sha ", "md5 ", "checksum ", "hash ") + letters(rng.choice([32, 40, 64]), hexa),
        lambda: cue("part ", "order no. ", "version ", "serial ", "build ") + phone(),
        lambda: cue("part ", "order ", "ticket ", "serial ") + f"{digits(3)}-{digits(2)}-{digits(4)}",
        lambda: cue("part ", "serial ", "order ") + blocks(),
        lambda: "AB12 " + " ".join(letters(4, up) for _ in range(4)),
        lambda: cue("", "example ") + cue("sk_test_", "ghp_", "xoxb-") + cue("x", "0", "your") * 6 + "xxxxxxxx",
        lambda: cue("the bearer ", "a bearer ") + word() + word() + word(),
        lambda: f"look {word()} (at) {word()} (dot) " + word()[:3] + "x",
    ]
    label = int(rng.random() < 0.5)
    return f"{fill()} {rng.choice(good if label else bad)()} {fill()}", label


@dataclass
class Model:
    forest: trees.Forest
    thresholds: dict[int, float]

    def accept(self, text: str, taken: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
        found = proposals(text)
        if not found:
            return []
        p = self.forest.proba(np.array([features(text, *f) for f in found]))
        best = sorted((-x, f) for x, f in zip(p, found, strict=True) if x >= self.thresholds[f[1]])
        out, busy = [], sorted((s, e) for s, _, e in taken)
        for _, (s, k, e) in best:
            i = bisect.bisect_left(busy, (s, e))
            if (i < len(busy) and busy[i][0] < e) or (i and busy[i - 1][1] > s):
                continue
            bisect.insort(busy, (s, e))
            out.append((s, k, e))
        return out


def cases(count: int, seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Features, labels and kinds of the proposals in so many made-up texts."""
    rng = random.Random(seed)
    rows, labels, kinds = [], [], []
    for _ in range(count):
        text, label = _case(rng)
        for f in proposals(text):
            rows.append(features(text, *f))
            labels.append(label)
            kinds.append(f[1])
    return np.array(rows), np.array(labels, float), np.array(kinds)


@lru_cache(maxsize=4)
def train(count: int = 9000, seed: int = 11, precision: float = 0.97) -> Model:
    x, y, k = cases(count, seed)
    half = len(x) * 2 // 3
    forest = trees.fit(x[:half], y[:half], trees=40)
    p, right, kind_of = forest.proba(x[half:]), y[half:], k[half:]
    thresholds = {}
    for kind in range(len(BASE), len(KINDS)):
        mine = kind_of == kind
        steps = np.unique(p[mine])
        fit = [t for t in steps if right[mine & (p >= t)].mean() >= precision]
        # the middle between the lowest threshold that is precise enough and the next lower score
        below = steps[steps < fit[0]] if fit else []
        thresholds[kind] = float((fit[0] + (below[-1] if len(below) else 0.0)) / 2) if fit else 0.5
    return Model(forest, thresholds)


def _name(spans) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


def find(docs: DataFrame, model: Model | None = None) -> DataFrame:
    """doc_id, counts of the base kinds, base_sha256, spans and n_added of every row."""
    model = model or train()

    def run(batches):
        for batch in batches:
            counts, digest, all_spans, added = [[], [], [], []], [], [], []
            for i in range(len(batch)):
                text = batch.column(1)[i].as_py() or ""
                base = base_spans(text)
                more = model.accept(text, base)
                for k in range(4):
                    counts[k].append(sum(b[1] == k for b in base))
                digest.append(hashlib.sha256(_name(base).encode()).hexdigest())
                all_spans.append(_name(sorted(base + more)))
                added.append(len(more))
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(c, pa.int64()) for c in counts], pa.array(digest, pa.string()), pa.array(all_spans, pa.string()), pa.array(added, pa.int64())], ["doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans", "n_added"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long")


def redact(text: str, model: Model) -> str:
    """The text with every span replaced by its kind in brackets; overlapping spans become one."""
    base = base_spans(text)
    out, at = [], 0
    for s, k, e in sorted(base + model.accept(text, base)):
        if s >= at:
            out.append(text[at:s] + f"[{KINDS[k]}]")
        at = max(at, e)
    return "".join(out) + text[at:]


def redacted(docs: DataFrame, model: Model | None = None) -> DataFrame:
    """Documents with redacted texts; null texts stay null."""
    model = model or train()

    def run(batches):
        for batch in batches:
            i = batch.schema.get_field_index("text")
            new = pa.array([None if t is None else redact(t, model) for t in batch.column(i).to_pylist()], pa.string())
            yield batch.set_column(i, "text", new)

    return docs.mapInArrow(run, docs.schema)
