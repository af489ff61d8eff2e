"""Personal data by candidates and gradient boosted trees, and the op8 query.

Base spans (e-mail, IP, card, phone) follow fixed formats and always stay.
High-recall generators propose further, overlapping spans: loosely separated
digit groups and addresses, spelled-out e-mail addresses, mixed tokens of 16
characters and more.  Boosted trees on format and context features, calibrated
on a fold of their own, give each a probability; the threshold of each kind is
the least one that reaches ``PRECISION`` on documents that the trees have not
seen.  Spans may overlap; redaction covers their union.

The trees learn from a bounded sample of documents.  Labels come from how an
example was made, not from its features: a base span written loosely in its own
context (``rewrite``) is a positive of its kind, the same with a wrong check
digit, length or part (``spoil``) a negative, and so is every other candidate of
the text.  For secrets the two views are kept apart: an assignment or a known
credential prefix gives the label, and the trees see the token's form only,
against long words and names joined from the text's own words.  So a secret
without any cue is found too.

Null and empty texts have no span.  Work is n log n in a text's candidates.
"""

from __future__ import annotations

import bisect
import hashlib
import math
import random
import re
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridsparse.llm import boosting, common

SAMPLE_DOCUMENTS = 8000
PRECISION = 0.95
LEAST_POSITIVES = 5  # held-out positives of a kind below which its threshold is DOUBTFUL
DOUBTFUL = 0.9
KINDS = ("email", "ip", "card", "phone", "secret")
BASE = KINDS[:4]

LOCAL = re.compile(r"[A-Za-z0-9._%+-]")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"(?<![0-9])[0-9]++(\.[0-9]++)(\.[0-9]++)(\.[0-9]++)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
#: Generators of candidates beyond the base formats.
DIGITS = re.compile(r"(?<![0-9])[0-9](?:[ .()/-]{0,2}[0-9]){6,24}(?![0-9])")
TOKEN = re.compile(r"(?<![A-Za-z0-9_-])[A-Za-z0-9_-]{16,}+")
LOOSE_IP = re.compile(r"(?<![0-9.])[0-9]{1,3}(?:[ ]?[\[({]?(?:\.|,|dot|DOT)[\])}]?[ ]?[0-9]{1,3}){3}(?![0-9])")
SPELLED = re.compile(r"[ \[(]{1,2}(?:at|AT)[ \])]{1,2}[A-Za-z0-9-]{2,40}(?:(?:[ \[(]{1,2}(?:dot|DOT)[ \])]{1,2}|\.)[A-Za-z0-9-]{2,20}){1,4}")
DOMAIN_ENDS = {"com", "org", "net", "edu", "gov", "info", "io", "de", "fr", "es", "it", "uk", "eu", "us", "ca", "ch", "at", "nl"}
CUES = re.compile(r"(?i)(phone|tel|call|mobile|mail|card|visa|account|token|secret|password|passwd|key|api)\W{0,6}$")
ASSIGNED = re.compile(r"(?i)(token|secret|password|passwd|key|api\w*)\s*[=:]\s*[\"']?$")
CREDENTIAL = re.compile(r"(?:AKIA|ASIA|ghp_|gho_|sk-|xox[abp]-|eyJ)")

Span = tuple[str, int, int]


def luhn(digits: str) -> bool:
    total = sum(map(int, digits[-1::-2])) + sum((0, 2, 4, 6, 8, 1, 3, 5, 7, 9)[int(d)] for d in digits[-2::-2])
    return total % 10 == 0


def emails(text: str) -> list[Span]:
    """Leftmost non-overlapping addresses, found from their at signs so that work stays linear."""
    out, free, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > free and LOCAL.match(text, start - 1):
            start -= 1
        found = DOMAIN.match(text, at + 1) if start < at else None
        if found:
            out.append(("email", start, found.end()))
            free = found.end()
        else:
            free = max(free, at)
        at = text.find("@", max(free, at + 1))
    return out


def base_spans(text: str) -> list[Span]:
    """The spans of the fixed formats, by start and then kind."""
    out = emails(text)
    out += [("ip", m.start(), m.end()) for m in IP.finditer(text) if all(_octet(p) for p in m[0].split("."))]
    for m in CARD.finditer(text):
        if m.end() - m.start() >= 14:
            digits = m[0].replace(" ", "").replace("-", "")
            if 14 <= len(digits) <= 19 and luhn(digits):
                out.append(("card", m.start(), m.end()))
    if "+" in text:
        out += [("phone", m.start(), m.end()) for m in PHONE.finditer(text) if 10 <= sum(map(str.isdigit, m[0])) <= 15]
    return sorted(out, key=_place)


def _octet(part: str) -> bool:
    part = part.lstrip("0")
    return len(part) <= 3 and int(part or 0) <= 255


def _place(span: Span) -> tuple[int, int, int]:
    return span[1], KINDS.index(span[0]), span[2]


def candidates(text: str) -> list[Span]:
    """Overlapping proposals of all generators."""
    out: list[Span] = []
    for m in DIGITS.finditer(text):
        start = m.start() - 1 if m.start() and text[m.start() - 1] in "+(" else m.start()
        out += [("card", m.start(), m.end()), ("phone", start, m.end())]
    out += [("ip", m.start(), m.end()) for m in LOOSE_IP.finditer(text)]
    out += [("secret", m.start(), m.end()) for m in TOKEN.finditer(text) if any(c.isdigit() for c in m[0])]
    if "dot" in text or "DOT" in text or "(at)" in text or "[at]" in text or " at " in text:
        free = 0
        for m in SPELLED.finditer(text):
            start = m.start()
            while start > free and LOCAL.match(text, start - 1):
                start -= 1
            if start < m.start():
                out.append(("email", start, m.end()))
            free = m.end()
    return out


def describe(text: str, span: Span) -> list[float]:
    """Format and context features of a candidate (for a secret: format only)."""
    kind, start, end = span
    body = text[start:end]
    digits = "".join(c for c in body if c in "0123456789")
    groups = re.findall(r"[0-9]+", body)
    words = re.findall(r"[A-Za-z]+", body)
    before, after = text[max(0, start - 24) : start], text[end : end + 2]
    counts = [body.count(c) for c in set(body)]
    entropy = -sum(c / len(body) * math.log2(c / len(body)) for c in counts)
    upper, lower = sum(map(str.isupper, body)), sum(map(str.islower, body))
    letters = "".join(words)
    turns = sum(x.isdigit() != y.isdigit() for x, y in zip(body, body[1:], strict=False))
    outside = [bool(CUES.search(before)), before[-1:].isalnum(), after[:1].isalnum()] if kind != "secret" else [0.0, 0.0, 0.0]
    return [
        float(KINDS.index(kind)), len(body), len(digits), len(groups), max(map(len, groups), default=0), min(map(len, groups), default=0),
        luhn(digits) if digits else 0.0, all(_octet(g) for g in groups), body.startswith("+"), body.count(" "), body.count("-"), body.count("."),
        body.count("(") + body.count(")"), upper / len(body), lower / len(body), entropy, sum(c in "0123456789abcdefABCDEF" for c in body) / len(body),
        max(map(len, words), default=0), sum(c in "aeiouAEIOU" for c in letters) / max(1, len(letters)), turns / len(body), body.count("_"), len(words),
        body.count("@"), max((len(w) for w in words[-1:]), default=0), bool(words) and words[-1].lower() in DOMAIN_ENDS, *outside,
    ]


def _plain(address: str, rng: random.Random) -> str:
    """An address, half of the time without its digits, so that these don't decide."""
    bare = re.sub(r"[0-9]+", "", address)
    return bare if rng.random() < 0.5 and LOCAL.match(bare) and "@." not in bare and ".." not in bare else address


def rewrite(span: Span, body: str, rng: random.Random) -> str:
    """A base span's text as people write it outside the fixed formats."""
    kind = span[0]
    if kind == "email":
        local, domain = _plain(body, rng).split("@")
        at, dot = rng.choice([(" at ", " dot "), (" (at) ", "."), ("(at)", "(dot)"), (" [at] ", " [dot] "), (" at ", ".")])
        return local + at + domain.replace(".", dot)
    if kind == "ip":
        return body.replace(".", rng.choice([" . ", "[.]", ",", "(.)", " dot ", "[dot]"]))
    digits = re.sub(r"[^0-9]", "", body)
    if kind == "card":
        return rng.choice([".", "/", "  ", " - "]).join(digits[k : k + 4] for k in range(0, len(digits), 4))
    area, mid, last = digits[-10:-7], digits[-7:-4], digits[-4:]
    return rng.choice(["{}-{}-{}", "({}) {}-{}", "{}.{}.{}", "001 {} {} {}", "1-{}-{}-{}", "{} {} {}", "{}/{}{}"]).format(area, mid, last)


def spoil(span: Span, body: str, rng: random.Random) -> str:
    """Something of a like look that is no such data: a wrong check digit, part or length, or no domain."""
    kind = span[0]
    if kind == "email":
        place = rng.choice(["noon", "home", "table", "page", "dawn"]) + rng.choice(["", "", str(rng.randrange(99))])
        return f"{_plain(body, rng).split('@')[0].split('.')[0]} at {place}.{rng.choice(['then', 'when', 'we', 'but', 'and 3.after'])}"
    if kind == "ip":
        parts = body.split(".")
        parts[rng.randrange(4)] = str(rng.randrange(256, 1000))
        return rng.choice([" . ", ",", "[.]", " dot "]).join(parts)
    digits = re.sub(r"[^0-9]", "", body)
    if kind == "card":
        wrong = digits[:-1] + str((int(digits[-1]) + rng.randrange(1, 10)) % 10)
        return rewrite(span, wrong, rng)
    return rng.choice([f"{digits[:4]}-{digits[4:6]}-{digits[6:8]}", f"{digits[:2]}.{digits[2:4]}.{digits[4:8]}", digits[:7], f"{digits[:3]} {digits[3:6]} {digits[6:8]}", digits[:8], f"{digits[:5]}/{digits[5:9]}"])


def long_names(text: str, rng: random.Random, number: int = 3) -> list[str]:
    """Long tokens with a digit that are no secrets, joined from the text's own words."""
    words = re.findall(r"[A-Za-z]{2,12}", text)
    out = []
    for _ in range(number if words else 0):
        parts = [rng.choice(words) for _ in range(rng.randrange(3, 7))]
        parts.insert(rng.randrange(len(parts) + 1), str(rng.choice([rng.randrange(10), rng.randrange(100), rng.randrange(1900, 2100), rng.randrange(10**6)])))
        out.append(rng.choice(["_", "-", "", "_"]).join(map(str.capitalize, parts) if rng.random() < 0.3 else parts))
    return [w for w in out if len(w) >= 16]


def examples(text: str) -> tuple[list[list[float]], list[bool]]:
    """Features and labels of training candidates from one text."""
    rng = random.Random(zlib.crc32(text.encode()))
    base = base_spans(text)
    rows, labels = [], []
    for span in candidates(text):
        kind, start, end = span
        if kind == "secret":
            mark = bool(ASSIGNED.search(text[max(0, start - 24) : start]) or CREDENTIAL.match(text, start))
            if not mark and any(a < end and start < b for _, a, b in base):
                continue  # a run of digits of some other kind: neither view speaks
        elif any(a <= start and end <= b for _, a, b in base):
            continue  # the base formats decide
        else:
            mark = False
        rows.append(describe(text, span))
        labels.append(mark)
    for span in base:
        head, body, tail = text[: span[1]], text[span[1] : span[2]], text[span[2] :]
        for make, mark in ((rewrite, True), (spoil, False)):
            made = make(span, body, rng)
            low, high = len(head[-64:]), len(head[-64:]) + len(made)
            near = head[-64:] + made + tail[:64]
            for c in candidates(near):
                if c[0] != "secret" and c[1] < high and low < c[2]:
                    rows.append(describe(near, c))
                    labels.append(mark and c[0] == span[0] and c[1] <= low + 1 and c[2] >= high - 1 and high - low >= 0.8 * (c[2] - c[1]))
    for name in long_names(text, rng):
        rows.append(describe(name, ("secret", 0, len(name))))
        labels.append(False)
    return rows, labels


@dataclass
class Detector:
    """Boosted trees, and the probability from which a candidate of each kind is kept."""

    trees: boosting.Boosted
    thresholds: dict[str, float]

    def probability(self, x: np.ndarray) -> np.ndarray:
        return self.trees.probability(x)


def fit(texts: list[str]) -> Detector | None:
    """Trees from four of five texts, thresholds from the fifth; None without candidates of both classes."""
    seen, held = ([], []), ([], [])
    for k, text in enumerate(texts):
        for into, found in zip(held if k % 5 == 4 else seen, examples(text), strict=True):
            into += found
    y = np.array(seen[1], bool)
    if not len(y) or y.all() or not y.any():
        return None
    trees = boosting.fit(np.array(seen[0], float), y)
    return Detector(trees, thresholds(trees, np.array(held[0], float), np.array(held[1], bool)))


def thresholds(trees: boosting.Boosted, x: np.ndarray, y: np.ndarray) -> dict[str, float]:
    """For each kind the least probability from which on ``PRECISION`` of the given candidates are positive."""
    out = dict.fromkeys(KINDS, DOUBTFUL)
    if not len(y):
        return out
    chance = trees.probability(x)
    for k, kind in enumerate(KINDS):
        own, right = chance[x[:, 0] == k], y[x[:, 0] == k]
        if right.sum() < LEAST_POSITIVES:
            continue
        order = np.argsort(-own, kind="stable")
        precision = np.cumsum(right[order]) / np.arange(1, len(order) + 1)
        last = np.append(own[order][1:] != own[order][:-1], True)  # a threshold takes all of equal probability
        good = np.flatnonzero((precision >= PRECISION) & last)
        out[kind] = float(max(0.5, own[order][good[-1]])) if len(good) else 2.0
    return out


def fit_from_documents(docs: DataFrame, sample: int = SAMPLE_DOCUMENTS) -> Detector | None:
    """Fit on about ``sample`` documents that hold a digit, drawn by id hash."""
    total = docs.count()
    draw = F.pmod(F.xxhash64(F.col("doc_id"), F.lit(8)), F.lit(1 << 30)) / F.lit(float(1 << 30))
    rows = docs.select("doc_id", "text").where((draw < F.lit(sample / max(1, total))) & F.col("text").rlike("[0-9]"))
    return common.fit_remotely(rows, _fit_rows)


def _fit_rows(rows: list[dict]) -> Detector | None:
    return fit([r["text"] for r in sorted(rows, key=lambda r: (r["doc_id"] is None, r["doc_id"], r["text"]))])


def find(text: str, model: Detector | None) -> tuple[list[Span], list[Span]]:
    """Base spans, and all spans: an added one may overlap others but lies inside no base span and no stronger added one."""
    base = base_spans(text)
    if model is None:
        return base, base
    starts, reach = [b[1] for b in base], [0]  # the farthest end of the base spans up to each
    for b in base:
        reach.append(max(reach[-1], b[2]))
    proposed = [c for c in candidates(text) if reach[bisect.bisect_right(starts, c[1])] < c[2]]
    if not proposed:
        return base, base
    chance = np.concatenate([model.probability(np.array([describe(text, c) for c in proposed[a : a + 4096]], float)) for a in range(0, len(proposed), 4096)])
    strong = [(p, c) for p, c in zip(chance.tolist(), proposed, strict=True) if p >= model.thresholds[c[0]]]
    strong.sort(key=lambda x: -x[0])
    return base, sorted(base + uncovered([c for _, c in strong]), key=_place)


def uncovered(spans: list[Span]) -> list[Span]:
    """Those ``spans``, strongest first, that lie inside no stronger one: a Fenwick tree holds the farthest end by start."""
    rank = {x: k + 1 for k, x in enumerate(sorted({c[1] for c in spans}))}
    farthest = [0] * (len(rank) + 1)
    out = []
    for span in spans:
        at, reach = rank[span[1]], 0
        while at:
            reach, at = max(reach, farthest[at]), at & (at - 1)
        if reach < span[2]:
            out.append(span)
            at = rank[span[1]]
            while at <= len(rank):
                farthest[at] = max(farthest[at], span[2])
                at += at & -at
    return out


def joined(spans: list[Span]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def redact(text: str, spans: list[Span]) -> str:
    """The text with each span (overlaps merged, the first kind named) replaced by its kind in brackets."""
    out, done = [], 0
    for kind, start, end in spans:
        if start >= done:
            out += [text[done:start], f"[{kind.upper()}]"]
        done = max(done, end)
    return "".join([*out, text[done:]])


HINT = re.compile(r"[0-9@]|dot|DOT|[(\[]at[)\]]| at ")
MARKS = np.zeros(256, bool)
MARKS[48:58] = MARKS[ord("@")] = True


def detect(docs: DataFrame, model: Detector | None, redacted: bool = False) -> DataFrame:
    """Spans of every row: base counts and digest, all spans, and (if asked) the redacted text.

    A text without a digit or an at sign is passed on unread unless it may hold a spelled-out address.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    none = hashlib.sha256(b"").hexdigest()

    def kernel(part: pa.RecordBatch) -> pa.RecordBatch:
        data, offsets = common.utf8(part.column("text"))
        found = np.concatenate(([0], np.cumsum(MARKS[data])))
        marked = found[offsets[1:]] > found[offsets[:-1]]
        n = part.num_rows
        counts = np.zeros((n, 4), np.int64)
        digest, spans, texts = [none] * n, [""] * n, [None] * n
        for r in range(n):
            text = data[offsets[r] : offsets[r + 1]].tobytes()
            if marked[r] or b"dot" in text or b"DOT" in text or b"(at)" in text or b"[at]" in text or b" at " in text:
                text = text.decode()
                base, every = find(text, shared.value)
                for kind, _, _ in base:
                    counts[r, BASE.index(kind)] += 1
                if base:
                    digest[r] = hashlib.sha256(joined(base).encode()).hexdigest()
                spans[r] = joined(every)
                if redacted:
                    texts[r] = redact(text, every)
            elif redacted:
                texts[r] = text.decode()
        columns = [part.column("doc_id"), *(pa.array(counts[:, k]) for k in range(4)), pa.array(digest, pa.string()), pa.array(spans, pa.string()), pa.array(texts, pa.string())]
        return pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans", "redacted"])

    return common.map_slices(docs.select("doc_id", "text"), kernel, "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, redacted string")


def redact_documents(docs: DataFrame, model: Detector | None) -> DataFrame:
    """``docs``, all columns, with the spans of each text replaced by their kinds and ``n_chars`` brought up to date."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def kernel(part: pa.RecordBatch) -> pa.RecordBatch:
        texts = part.column("text").to_pylist()
        sizes = part.column("n_chars").to_pylist() if "n_chars" in part.schema.names else None
        for i, text in enumerate(texts):
            if text and HINT.search(text):
                texts[i] = redact(text, find(text, shared.value)[1])
                if sizes and sizes[i] is not None:
                    sizes[i] = len(texts[i])
        out = part.set_column(part.schema.get_field_index("text"), "text", pa.array(texts, part.column("text").type))
        if sizes:
            out = out.set_column(out.schema.get_field_index("n_chars"), "n_chars", pa.array(sizes, part.column("n_chars").type))
        return out

    return common.map_slices(docs, kernel, docs.schema)


def op8_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's personal data."""
    docs = common.read_table(spark, sf_dir, "documents")
    return detect(docs, fit_from_documents(docs)).drop("redacted")
