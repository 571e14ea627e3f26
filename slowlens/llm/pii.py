"""Personal data: generators propose overlapping spans, boosted trees score them, calibrated thresholds select.

Base spans (email, ip, card, phone) follow fixed patterns and always stay. Beyond them generators with high recall
propose secrets, spelled-out addresses, local phone numbers, account numbers, identity numbers and long addresses;
gradient-boosted trees judge each candidate by its format and its surroundings. The trees are trained here, on
candidates drawn by a seeded generator of true and look-alike spans in invented surroundings (TRAIN of them), in which
words that announce a kind stand before look-alikes as well. Thresholds are calibrated on spans of other lengths, alphabets
and surroundings than the trees have seen: each kind gets the lowest score whose precision there reaches PRECISION.

Every whole text is searched for every kind; a kind's generators are skipped only where the text lacks what each of
their matches holds. Spans have no greatest length. Cases: null text counts as empty; repeated rows are each
searched; an empty table gives no rows; further columns are ignored.
"""

from __future__ import annotations

import bisect
import hashlib
import math
import random
import re
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from slowlens.llm.common import slices, table

BASE = ("email", "ip", "card", "phone")
ADDED = ("secret", "email_text", "phone_local", "iban", "ssn", "ipv6")
TRAIN, TREES, DEPTH, RATE, PRECISION, SEED = 6000, 60, 3, 0.2, 0.97, 7

_domain = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++")
_local = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_ip = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_card = re.compile(r"[0-9](?:[ -]?[0-9])++")
_phone = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_digits = re.compile(r"[0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        n = int(c)
        if i % 2:
            n = n * 2 - 9 if n > 4 else n * 2
        total += n
    return total % 10 == 0


def _emails(text: str) -> Iterator[tuple[int, int]]:
    """From each at sign the local part reaches back to the last match, the domain is read forward: linear time."""
    free, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > free and text[start - 1] in _local:
            start -= 1
        m = _domain.match(text, at + 1) if start < at else None
        if m:
            yield start, m.end()
            free = m.end()
        else:
            free = at + 1
        at = text.find("@", max(free, at + 1))


def _octets(s: str) -> bool:
    return all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in s.split("."))


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """By kind as in BASE, then by start."""
    out: list[tuple[str, int, int]] = []
    if "@" in text:
        out += [("email", *x) for x in _emails(text)]
    if _digits.search(text):
        out += [("ip", m.start(), m.end()) for m in _ip.finditer(text) if _octets(m[0])]
        for m in _card.finditer(text):
            s = m[0].replace(" ", "").replace("-", "")
            if 13 <= len(s) <= 19 and luhn(s):
                out.append(("card", m.start(), m.end()))
        if "+" in text:
            out += [("phone", m.start(), m.end()) for m in _phone.finditer(text) if 9 <= len(_digits.findall(m[0])) <= 15]
    return out


_GENERATORS = {
    "secret": [re.compile(r"(?i)(?:token|secret|api[_-]?key|passw(?:or)?d|pwd|credential|key)[\"']?[ ]{0,2}[:=][ ]{0,2}[\"']?([^\s\"'&]{6,}+)"), re.compile(r"(?<![A-Za-z0-9_+/-])([A-Za-z0-9_+/-]{20,}+)")],
    "email_text": [
        re.compile(r"(?i)(?<![A-Za-z0-9._-])([A-Za-z0-9._-]+ ?[\[(<{] ?at ?[\])>}] ?[A-Za-z0-9-]{1,63}(?: ?[\[(<{]? ?(?:dot|\.) ?[\])>}]? ?[A-Za-z]{2,24}){1,3})(?![A-Za-z0-9])"),
        re.compile(r"(?i)(?<![A-Za-z0-9._-])([A-Za-z0-9._-]+ at [A-Za-z0-9-]{1,63}(?:\.[A-Za-z]{2,24}| ?[\[(<{]? ?dot ?[\])>}]? ?[A-Za-z]{2,24}){1,3})(?![A-Za-z0-9])"),
    ],
    "phone_local": [re.compile(r"(?<![0-9+])(\(?[0-9]{3}\)?[ .-]{1,2}[0-9]{3}[ .-][0-9]{4})(?![0-9])")],
    "iban": [re.compile(r"(?<![A-Za-z0-9])([A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?)(?![A-Za-z0-9])")],
    "ssn": [re.compile(r"(?<![0-9-])([0-9]{3}-[0-9]{2}-[0-9]{4})(?![0-9-])")],
    "ipv6": [re.compile(r"(?<![0-9A-Za-z:])((?:[0-9A-Fa-f]{1,4}:){3,7}[0-9A-Fa-f]{1,4})(?![0-9A-Za-z:])")],
}
_at = re.compile(r"[aA][tT] ?[\])>}]? ?[A-Za-z0-9-]")
_needs = {  # what any match of a kind's patterns holds, so a text without it needs no search
    "email_text": lambda t: _at.search(t),
    **{k: _digits.search for k in ("phone_local", "iban", "ssn")},
    "ipv6": lambda t: t.count(":") >= 3,
}
_cue = {"secret": ("token", "secret", "key", "passw", "pwd", "credential"), "email_text": ("mail", "contact", "write", "reach"), "phone_local": ("phone", "tel", "call", "fax", "mobile"), "iban": ("iban", "account", "bank"), "ssn": ("ssn", "social", "security"), "ipv6": ("ip", "host", "address")}
_apart = re.compile(r"(?i)[^a-z]at[^a-z]")
_ends = frozenset("com org net edu gov info biz io co uk us de fr es it nl ch at eu ca au jp in br".split())
_strong = ("passw", "pwd", "secret", "credential", "api_key", "api-key", "apikey")  # what follows these is meant to be kept
_vowels = frozenset("aeiouAEIOU")


def candidates(text: str) -> list[tuple[str, int, int]]:
    """Overlapping spans of the added kinds; each start is proposed once a kind."""
    out = set()
    for kind, patterns in _GENERATORS.items():
        if kind in _needs and not _needs[kind](text):
            continue
        for p in patterns:
            out.update((kind, *m.span(1)) for m in p.finditer(text))
    return sorted(out)


def features(text: str, kind: str, start: int, end: int) -> list[float]:
    s = text[start:end]
    n = len(s)
    seen = Counter(s)
    digits = sum(map(str.isdigit, s))
    letters = sum(map(str.isalpha, s))
    left, right = text[max(0, start - 30) : start], text[end : end + 12]
    cue = left.lower()
    a, b = (left[-1:] or " "), (right[:1] or " ")
    compact = re.sub(r"[^A-Za-z0-9]", "", s)
    mod97 = 0.0
    if kind == "iban" and compact.isascii() and len(compact) >= 15:
        mod97 = float(int("".join(str(int(c, 36)) for c in compact[4:] + compact[:4])) % 97 == 1)
    return [
        *(float(kind == k) for k in ADDED), math.log(n), digits / n, letters / n, -sum(c / n * math.log2(c / n) for c in seen.values()), len(seen) / n,
        sum(c in _vowels for c in s) / max(1, letters), float(bool(re.fullmatch(r"[0-9a-f]+|[0-9A-F]+", s))), float(any(map(str.isupper, s)) and any(map(str.islower, s))),
        sum(x.isdigit() != y.isdigit() for x, y in zip(s, s[1:], strict=False)) / n, float(sum(not c.isalnum() for c in s)), float(any(k in cue for k in _cue[kind])), float(any(k in cue for k in _strong)), _letter_pairs(s),
        float(a in "\"'"), float(b in "\"'"), float(a in "=:" or left.rstrip()[-1:] in ("=", ":")), float(a.isalnum()), float(b.isalnum()), mod97, float(bool(re.search(r"[\[(<{] ?(?:at|dot) ?[\])>}]", s, re.I))),
        float(s[:3] in ("000", "666") or s[:1] == "9"), float("dot" in s.lower()), float("/" in s),
        float(len({c for c in s if not c.isalnum()})), float(a in "/%#" or b in "/%#"), float(left.rstrip()[-1:].isdigit() or right.lstrip()[:1].isdigit()), float(bool(_apart.search(s))), float(re.split(r"[^a-z]+", s.lower().rstrip(")]}>"))[-1] in _ends), float(bool(re.search(r"\. ?[A-Z]|\. ", s))),
    ]


_usual = frozenset("th he in er an re on at en nd ti es or te of ed is it al ar st to nt ng se ha as ou io le ve co me de hi ri ro ic ne ea ra ce li ch ll be ma si om ur la el ns di ss us ec".split())


def _letter_pairs(s: str) -> float:
    """Share of neighbouring letters that are usual in words."""
    low = s.lower()
    pairs = [low[i : i + 2] for i in range(len(low) - 1) if low[i : i + 2].isalpha()]
    return sum(p in _usual for p in pairs) / len(pairs) if pairs else 0.0


class BoostedTrees:
    """Binary trees of fixed depth on the logistic loss; splits at quantiles, leaves by Newton steps."""

    def __init__(self, x: np.ndarray, y: np.ndarray, trees: int = TREES, depth: int = DEPTH, rate: float = RATE):
        self.depth, self.start, self.trees = depth, math.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6)), []
        cuts = [np.unique(np.quantile(c, np.linspace(0.02, 0.98, 25))) for c in x.T]
        margin = np.full(len(y), self.start)
        for _ in range(trees):
            p = 1 / (1 + np.exp(-margin))
            g, h = y - p, p * (1 - p)
            nodes, at = [(0, 0.0)] * (2**depth - 1), np.zeros(len(y), int)
            for k in range(2**depth - 1):
                mine = at == k
                if mine.sum() < 2:
                    nodes[k] = (0, math.inf)
                else:
                    best, xm, gm, hm = (-1.0, 0, math.inf), x[mine], g[mine], h[mine]
                    for f, values in enumerate(cuts):
                        right = xm[:, f : f + 1] > values
                        gr, hr = gm @ right, hm @ right
                        gain = gr**2 / (hr + 1) + (gm.sum() - gr) ** 2 / (hm.sum() - hr + 1)
                        j = int(np.argmax(gain))
                        if gain[j] > best[0]:
                            best = (float(gain[j]), f, float(values[j]))
                    nodes[k] = best[1:]
                at[mine] = 2 * k + 1 + (x[mine, nodes[k][0]] > nodes[k][1])
            leaf = at - (2**depth - 1)
            values = np.array([rate * g[leaf == i].sum() / (h[leaf == i].sum() + 1) for i in range(2**depth)])
            margin += values[leaf]
            self.trees.append((np.array([n[0] for n in nodes]), np.array([n[1] for n in nodes]), values))

    def probability(self, x: np.ndarray) -> np.ndarray:
        margin = np.full(len(x), self.start)
        rows = np.arange(len(x))
        for feature, cut, value in self.trees:
            at = np.zeros(len(x), int)
            for _ in range(self.depth):
                at = 2 * at + 1 + (x[rows, feature[at]] > cut[at])
            margin += value[at - (2**self.depth - 1)]
        return 1 / (1 + np.exp(-margin))


def _examples(rng: random.Random, n: int, other: bool = False) -> Iterator[tuple[str, str, bool]]:
    """(text, kind, whether the spans of that kind in it are personal data), true ones and look-alikes in turn; `other`
    draws lengths, syllables and surroundings of its own."""
    syllables = ["ka", "to", "mir", "sen", "lo", "ver", "da", "pel", "nor", "sti", "qu", "ay"] if other else ["th", "er", "in", "on", "es", "la", "de", "ch", "ou", "ti", "an", "be", "ie"]
    stretch = 1.4 if other else 1.0
    word = lambda: "".join(rng.choice(syllables) for _ in range(rng.randint(1, 4)))
    text = lambda k: " ".join(word() for _ in range(k))
    draw = lambda k, a="0123456789abcdef": "".join(rng.choice(a) for _ in range(k))
    some = lambda a, b: rng.randint(a, int(b * stretch))
    num = lambda k: draw(k, "0123456789")
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    mixed = upper + lower + "0123456789"

    def iban(valid: bool = True) -> str:
        country, body = rng.choice(["DE", "FR", "ES", "GB", "NL", "IT"]), num(rng.randint(14, 20))
        check = 98 - int(body + "".join(str(int(c, 36)) for c in country) + "00") % 97
        check = check if valid else (check + rng.randint(1, 95)) % 97
        compact = f"{country}{check:02d}{body}"
        return " ".join(compact[i : i + 4] for i in range(0, len(compact), 4)) if rng.random() < 0.3 else compact

    def secret() -> str:
        strong, weak = rng.choice(["password", "passwd", "pwd", "secret", "api_key", "api-key", "credential"]), rng.choice(["token", "key"])
        q, sign = rng.choice(['"', "'", ""]), rng.choice(["=", ": ", " = ", ":"])
        strange = rng.choice([draw(some(16, 64)), draw(some(16, 48), mixed), rng.choice(["AK", "gp_", "sk-", "xo-"]) + draw(some(12, 36), mixed), draw(some(16, 40), upper + "0123456789"), draw(some(18, 40), lower), draw(some(16, 800), mixed + "+/")])
        chosen = rng.choice([draw(some(8, 20), mixed + "!#$%*?@"), word() + word() + num(rng.randint(1, 4)), word() + word() + draw(some(4, 10), lower), word() + draw(3, "!#$") + num(3)])
        alone = draw(some(24, 64)) if rng.random() < 0.5 else draw(some(24, 48), mixed)
        return rng.choice([f"{strong}{sign}{q}{strange}{q}", f"{weak}{sign}{q}{strange}{q}", f"{strong}{sign}{q}{chosen}{q}", alone])

    def no_secret() -> str:
        weak, run = rng.choice(["token", "key"]), some(4, 9)
        sign = rng.choice(["=", ": ", " = "])
        words = lambda by, k: by.join(word() for _ in range(k))
        return rng.choice([words("", run + 2), words("-", run), words("/", run), words("_", run), f"{weak}{sign}{words('', 3)}", f"{weak}{sign}{words('-', 5)}", num(some(20, 40)), "-" * some(20, 40), "/" + words("/", run) + "/" + num(4), words("", run + 2).upper()])

    for i in range(n):
        kind, true = ADDED[i % len(ADDED)], (i // len(ADDED)) % 2 == 0
        if kind == "secret":
            s = secret() if true else no_secret()
        elif kind == "email_text":
            dot = rng.choice(["dot", "[dot]", "(dot)"])
            s = f"{word()}{rng.choice(['', '.' + word(), num(2)])} {rng.choice(['[at]', '(at)', 'at', '{at}'])} {word()} {dot} {rng.choice(['com', 'org', 'net', 'de', 'io'])}" if true else rng.choice([f"{word()} at {word()}.{word().capitalize()}", f"{word()} at {word()}. {word()}", f"{word()} at {word()} dot {word()}{word()}", f"{word()} at {word()}.{word()}{word()}", f"{word()} (at {word()}) {word()}", f"{word()} (at) {word()}. {word().capitalize()}"])
        elif kind == "phone_local":
            s = rng.choice([f"({num(3)}) {num(3)}-{num(4)}", f"{num(3)}-{num(3)}-{num(4)}", f"{num(3)}.{num(3)}.{num(4)}", f"{num(3)} {num(3)} {num(4)}"]) if true else rng.choice([f"{num(3)} {num(3)} {num(4)} {num(3)}", f"={num(3)}.{num(3)}.{num(4)}%", f"{num(3)}.{num(3)} {num(4)}", f"/{num(3)}-{num(3)}-{num(4)}/"])
        elif kind == "iban":
            s = iban() if true else rng.choice([iban(False), f"{rng.choice(['AB', 'XK', 'DE'])}{num(2)}{draw(rng.choice([12, 16, 20]), upper + '0123456789')}"])
        elif kind == "ssn":
            s = f"{rng.randint(1, 8)}{num(2)}-{num(2)}-{num(4)}" if true else rng.choice([f"{rng.choice(['000', '666', '9' + num(2)])}-{num(2)}-{num(4)}", f"/{num(3)}-{num(2)}-{num(4)}"])
        else:
            s = ":".join(draw(rng.choice([4, 4, 4, rng.randint(1, 4)])) for _ in range(8)) if true else ":".join(num(2) for _ in range(rng.randint(4, 6)))
        cue = rng.choice(_cue[kind]) + rng.choice([" ", ": "]) if rng.random() < 0.4 and kind != "secret" else ""
        yield f"{text(rng.randint(0, 4))} {cue}{s} {text(rng.randint(0, 4))}", kind, true


def _sample(rng: random.Random, n: int, other: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Features, truth and kind of the candidates in n examples."""
    x, y, kinds = [], [], []
    for text, kind, true in _examples(rng, n, other):
        for k, a, b in candidates(text):
            if k == kind:
                x.append(features(text, k, a, b))
                y.append(float(true))
                kinds.append(k)
    return np.array(x), np.array(y), np.array(kinds)


@lru_cache(maxsize=1)
def trained(n: int = TRAIN, seed: int = SEED) -> tuple[BoostedTrees, dict[str, float]]:
    """The trees and each kind's threshold."""
    x, y, _ = _sample(random.Random(seed), n, False)
    trees = BoostedTrees(x, y)
    x, y, kinds = _sample(random.Random(seed + 1), n // 2, True)
    p = trees.probability(x)
    limits = {}
    for k in ADDED:
        own = kinds == k
        order = np.argsort(-p[own], kind="stable")
        score, hit = p[own][order], y[own][order]
        last = np.r_[score[1:] != score[:-1], True]  # a threshold takes all of equal score
        good = np.flatnonzero((np.cumsum(hit) / np.arange(1, len(hit) + 1) >= PRECISION) & last)
        limits[k] = float(score[good[-1]]) if len(good) else 1.1
    return trees, limits


Spans = list[tuple[str, int, int]]


def redactions(text: str | None, trees: BoostedTrees, limits: dict[str, float]) -> tuple[Spans, Spans]:
    """Base spans, and the selected added ones by kind and start. Among overlapping added
    spans the likeliest stays; one that lies within a base span adds nothing and is left out."""
    return all_redactions([text], trees, limits)[0]


def all_redactions(texts: list[str | None], trees: BoostedTrees, limits: dict[str, float]) -> list[tuple[Spans, Spans]]:
    """redactions() of each text; the trees judge the candidates of all texts at once."""
    found = [candidates(t) if t else [] for t in texts]
    rows = [features(t, *c) for t, own in zip(texts, found, strict=True) for c in own]
    p = trees.probability(np.array(rows)) if rows else np.zeros(0)
    out, at = [], 0
    for t, own in zip(texts, found, strict=True):
        base = base_spans(t) if t else []
        out.append((base, _selected(base, own, p[at : at + len(own)], limits)))
        at += len(own)
    return out


def _selected(base: Spans, found: Spans, p: np.ndarray, limits: dict[str, float]) -> Spans:
    chosen: list[tuple[int, int]] = []
    added = []
    starts, ends = [], []  # of base spans by start, and how far those up to each reach
    for _, x, y in sorted(base, key=lambda s: s[1]):
        starts.append(x)
        ends.append(max(y, ends[-1] if ends else 0))

    def inside(a: int, b: int) -> bool:
        i = bisect.bisect(starts, a)
        return i > 0 and ends[i - 1] >= b

    for i in sorted(range(len(found)), key=lambda i: (-p[i], found[i][1] - found[i][2], found[i])):
        kind, a, b = found[i]
        if p[i] < limits[kind]:
            continue
        at = bisect.bisect(chosen, (a, b))
        if (at and chosen[at - 1][1] > a) or (at < len(chosen) and chosen[at][0] < b) or inside(a, b):
            continue
        chosen.insert(at, (a, b))
        added.append(found[i])
    return sorted(added, key=lambda s: (ADDED.index(s[0]), s[1]))


def redact(text: str, spans: list[tuple[str, int, int]]) -> str:
    """Each stretch covered by spans becomes the name of the first span in it."""
    out, at = [], 0
    for kind, a, b in sorted(spans, key=lambda s: (s[1], -s[2])):
        if a >= at:
            out += [text[at:a], f"[{kind.upper()}]"]
        at = max(at, b)
    return "".join([*out, text[at:]])


def find_personal_data(docs: DataFrame, with_text: bool = False) -> DataFrame:
    """doc_id, counts by kind and spans of every document; `with_text` adds the redacted text."""
    trees, limits = trained()
    joined = lambda spans: ",".join(f"{k}:{a}:{b}" for k, a, b in spans)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            texts = batch.column("text").to_pylist()
            found = all_redactions(texts, trees, limits)
            counts = [[sum(s[0] == k for s in base) for base, _ in found] for k in BASE]
            cols = [batch.column("doc_id"), *(pa.array(c, pa.int64()) for c in counts), pa.array([hashlib.sha256(joined(b).encode()).hexdigest() for b, _ in found], pa.string()), pa.array([joined([*b, *a]) for b, a in found], pa.string())]
            cols += [pa.array([sum(s[0] == k for s in added) for _, added in found], pa.int64()) for k in ADDED]
            cols.append(pa.array([len(b) + len(a) for b, a in found], pa.int64()))
            if with_text:
                cols.append(pa.array([None if t is None else redact(t, [*b, *a]) for t, (b, a) in zip(texts, found, strict=True)], pa.string()))
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", *(f"n_{k}" for k in BASE), "base_sha256", "spans", *(f"n_{k}" for k in ADDED), "n_spans", *["redacted"] * with_text])

    schema = "doc_id bigint, n_email bigint, n_ip bigint, n_card bigint, n_phone bigint, base_sha256 string, spans string, " + ", ".join(f"n_{k} bigint" for k in ADDED) + ", n_spans bigint" + ", redacted string" * with_text
    return docs.select("doc_id", "text").mapInArrow(run, schema)


def op1_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_personal_data(table(spark, sf_dir, "documents"))
