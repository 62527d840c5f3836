"""Personal data: pattern spans, and a linear-chain conditional random field over word-shape features.

The field is trained in numpy on a small labelled table (``examples`` makes one from a seed) and decoded by Viterbi
in batches: words of many documents form one chain with edges between documents; a word whose best label is
O whatever its neighbours are (a bound over the transition weights shows it) splits the chain, and the segments
that are left are decoded together, one step for all.  Shapes of words met before are looked up.

Null or empty text: no spans.  Repeated rows: each gets its row.  Empty table: no rows.
"""

from __future__ import annotations

import hashlib
import random
import re
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import pick

KINDS = ["email", "ip", "card", "phone", "secret"]
LABELS = ["O", *KINDS]
#: Shapes of words that a worker keeps between batches.
CACHED_WORDS = 400_000

_LOCAL_CHARS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP_HINT, _IP = re.compile(r"[0-9]\.[0-9]"), re.compile(r"(?<![0-9])[0-9]+(?:\.[0-9]+){3}")
_CARD_HINT, _CARD = re.compile(r"[0-9](?:[ -]?[0-9]){13}"), re.compile(r"(?<![0-9])[0-9](?:[ -]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_WORD = re.compile(r"[^ \t\n\r\x0b\x0c]+")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if i % 2 == 0 else d * 2 - 9 * (d > 4)
    return total % 10 == 0


def digits_of(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def emails(text: str) -> list[tuple[int, int]]:
    """Leftmost non-overlapping addresses: around each @ in turn, the run of local characters before it and a dotted domain after it."""
    found, free, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > free and text[start - 1] in _LOCAL_CHARS:
            start -= 1
        domain = _DOMAIN.match(text, at + 1) if start < at else None
        if domain:
            found.append((start, domain.end()))
        free = domain.end() if domain else at + 1
        at = text.find("@", free)
    return found


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) by start, then kind."""
    found = []
    if "@" in text:
        found += [(s, e, "email") for s, e in emails(text)]
    if _IP_HINT.search(text):
        found += [(*m.span(), "ip") for m in _IP.finditer(text) if all(len(d := p.lstrip("0")) <= 3 and int(d or 0) <= 255 for p in m[0].split("."))]
    if _CARD_HINT.search(text):
        for m in _CARD.finditer(text):
            d = digits_of(m[0]) if m.end() - m.start() < 60 else ""
            if 14 <= len(d) <= 19 and luhn(d):
                found.append((*m.span(), "card"))
    if "+" in text:
        found += [(*m.span(), "phone") for m in _PHONE.finditer(text) if 10 <= sum("0" <= c <= "9" for c in m[0]) <= 15]
    return sorted(found, key=lambda x: (x[0], KINDS.index(x[2])))


# Word shapes


def features(word: str) -> tuple[tuple[str, ...], str]:
    """Features of a word's shape, and the coarse class that its neighbours see."""
    core = word.strip("\"'`,.;:!?()[]{}<>|*#$%&=")
    if not core:
        return ("punct", "p=" + word[:1]), "punct"
    if core.isalpha():
        c = "alpha" if len(core) < 25 else "alphalong"
        cue = core.lower() if core.lower() in _CUES else ""
        return (c, "cue=" + cue), "cue=" + cue if cue else c
    d = digits_of(core)
    n = len(d)
    size = "0" if n == 0 else "1-2" if n < 3 else "3" if n == 3 else "4" if n == 4 else "5-9" if n < 10 else "10-13" if n < 14 else "14-19" if n < 20 else "20+"
    shape = re.sub(r"(.)\1+", r"\1", "".join("d" if "0" <= c <= "9" else "x" if c.isalpha() else c for c in core))
    own = [f"shape={shape[:12]}", f"digits={size}", f"len={min(len(core) // 8, 5)}"]
    kind = f"n{size}"
    if shape == "d" and len(core) == n:
        own.append("number")
        if 14 <= n <= 19:
            own.append("luhn" if luhn(d) else "noluhn")
            kind += "l" if luhn(d) else "b"
    elif re.fullmatch(r"[0-9A-Za-z_\-/+]{20,}", core) and n >= 4 and sum(c.isalpha() for c in core) >= 4:
        own.append("key" + (":hex" if re.fullmatch("[0-9a-fA-F]+", core) else ""))
        kind = "key"
    if re.fullmatch(r"[0-9]{1,3}(\.[0-9]{1,3}){3}", core):
        fits = all(int(p) < 256 for p in core.split("."))
        own.append("quad" if fits else "badquad")
        kind = "quad"
    if "@" in core:
        own.append("at" + (":dot" if re.search(r"@[^@]+\.", core) else ""))
        kind = "at"
    if core[0] == "+":
        own.append("plus")
        kind = "plus"
    if word[0] == "(" and word[-1] == ")":
        own.append("paren")
    return tuple(own), kind


#: Words that say what follows.
_CUES = {"token", "secret", "password", "key", "apikey", "phone", "tel", "call", "card", "visa", "email", "mail", "ip", "host"}


def examples(n: int = 900, seed: int = 5) -> list[tuple[list[str], list[str]]]:
    """The small labelled table: lines of 18 words with a label each, made from a seed."""
    rng = random.Random(seed)
    alphabet = "etaoinshrdlucmfwypvbgkéèöüñß"

    def word() -> str:
        w = "".join(rng.choice(alphabet) for _ in range(rng.randint(1, 14)))
        w = w.capitalize() if rng.random() < 0.15 else w
        return w + rng.choice(["", "", "", "", ",", ".", "%%%", "$$$", "###", "***", "&&&", "-" + w, "'s"]) if rng.random() < 0.6 else w

    def digits(k: int) -> str:
        return "".join(rng.choice("0123456789") for _ in range(k))

    def card() -> str:
        body = digits(rng.choice([14, 15, 15, 15]))
        return body + next(c for c in "0123456789" if luhn(body + c))

    def bad_card() -> str:
        body = digits(15)
        return body + rng.choice([c for c in "0123456789" if not luhn(body + c)])

    def quad(top: int = 255) -> str:
        return ".".join(str(rng.randint(0, top)) for _ in range(4))

    made = []
    for _ in range(n):
        words, labels = [], []
        while len(words) < 18:
            r = rng.random()
            if r > 0.25:
                some = [(word(), "O")]
            elif r > 0.21:
                some = [(digits(rng.randint(1, 9)), "O")]
            elif r > 0.19:
                some = [(rng.choice(["|", "=", "-", "§ 3.2", "3.14", "1,200", "v2.0.1", bad_card(), bad_card(), digits(12), digits(24), "2024-01-05", "12:30", "+", "@", "a@b", f"{rng.randint(256, 999)}.{quad()[:7]}.1"]).split()[0], "O")]
            elif r > 0.16:
                some = [(word().lower().strip(",.%$#*&'") + rng.choice([".", "", "_"]) + digits(2) + "@mail" + digits(1) + rng.choice([".example.com", ".org", ".example.net"]), "email")]
            elif r > 0.12:
                some = [(quad(), "ip")]
            elif r > 0.08:
                some = [(card(), "card")]
            elif r > 0.04:
                some = [(w, "phone") for w in rng.choice([f"+{rng.randint(1, 99)} ({digits(3)}) {digits(3)}-{digits(4)}", f"+{rng.randint(1, 99)} {digits(3)} {digits(3)} {digits(4)}", f"({digits(3)}) {digits(3)}-{digits(4)}"]).split()]
            else:
                key = "".join(rng.choice("0123456789abcdef") for _ in range(rng.choice([32, 40, 40, 64])))
                some = [(rng.choice(["token", "secret", "key", "password"]), "O"), ("=", "O"), (f'"{key}"', "secret")] if rng.random() < 0.8 else [(key, "secret")]
            words += [w for w, _ in some]
            labels += [x for _, x in some]
        made.append((words[:18], labels[:18]))
    return made


@dataclass
class Field:
    """Weights: by feature and label for a word itself, by coarse class and label for its two neighbours, and by pair of labels."""

    own: dict[str, np.ndarray] = field(default_factory=dict)
    before: dict[str, np.ndarray] = field(default_factory=dict)
    after: dict[str, np.ndarray] = field(default_factory=dict)
    moves: np.ndarray = field(default_factory=lambda: np.zeros((len(LABELS), len(LABELS))))


def fit(table: list[tuple[list[str], list[str]]], steps: int = 150, rate: float = 0.15, decay: float = 2e-4) -> Field:
    """Maximum likelihood by Adam over the whole table; lines are padded with edges, whose label is O."""
    names: dict[tuple[str, str], int] = {}
    k, most = len(LABELS), max(len(w) for w, _ in table)
    rows, truth = [], np.zeros((len(table), most), int)
    for i, (words, labels) in enumerate(table):
        seen = [features(w) for w in words] + [(("edge",), "edge")] * (most - len(words))
        truth[i, : len(labels)] = [LABELS.index(x) for x in labels]
        for t, (mine, _) in enumerate(seen):
            keys = [("own", f) for f in mine] + [("before", seen[t - 1][1] if t else "edge"), ("after", seen[t + 1][1] if t + 1 < most else "edge")]
            rows += [(i * most + t, names.setdefault(key, len(names))) for key in keys]
    at, ids = np.array(rows).T
    w, moves = np.zeros((len(names), k)), np.zeros((k, k))
    state = [[np.zeros_like(x), np.zeros_like(x)] for x in (w, moves)]
    n = len(table)
    gold = np.eye(k)[truth]
    gold_w = np.zeros_like(w)
    np.add.at(gold_w, ids, gold.reshape(-1, k)[at])
    gold_moves = np.einsum("ita,itb->ab", gold[:, :-1], gold[:, 1:])
    for step in range(1, steps + 1):
        e = np.zeros((n * most, k))
        np.add.at(e, at, w[ids])
        e = e.reshape(n, most, k)
        forward, backward = np.empty_like(e), np.zeros_like(e)
        forward[:, 0] = e[:, 0]
        lse = lambda x, axis: (m := x.max(axis=axis, keepdims=True)).squeeze(axis) + np.log(np.exp(x - m).sum(axis=axis))
        for t in range(1, most):
            forward[:, t] = e[:, t] + lse(forward[:, t - 1, :, None] + moves, 1)
        for t in range(most - 2, -1, -1):
            backward[:, t] = lse(moves + (e[:, t + 1] + backward[:, t + 1])[:, None, :], 2)
        z = lse(forward[:, -1], 1)
        p = np.exp(forward + backward - z[:, None, None])
        pair = np.exp(forward[:, :-1, :, None] + moves + (e + backward)[:, 1:, None, :] - z[:, None, None, None]).sum(axis=(0, 1))
        got = np.zeros_like(w)
        np.add.at(got, ids, p.reshape(-1, k)[at])
        for x, g, (m, v) in zip((w, moves), ((got - gold_w) / n + decay * w, (pair - gold_moves) / n + 10 * decay * moves), state, strict=True):
            m *= 0.9
            m += 0.1 * g
            v *= 0.99
            v += 0.01 * g * g
            x -= rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    out = Field(moves=moves)
    for (side, name), i in names.items():
        getattr(out, side)[name] = w[i]
    return out


class Tagger:
    """Labels words of many texts at once under a Field."""

    def __init__(self, model: Field):
        self.model = model
        self.types: dict = {}
        self.rows: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.known: dict[str, int] = _Shapes(self)
        self.edge = self.type_of((("edge",), "edge"))
        edge = self.rows[self.edge]
        self.rows[self.edge] = (np.array([1e6] + [0.0] * len(KINDS)), edge[1], edge[2])
        t = model.moves
        # what a path can gain at most by another label than O at a place
        self.bound = (t - t[:, :1]).max(axis=0) + (t - t[:1, :]).max(axis=1)

    def type_of(self, key) -> int:
        if key not in self.types:
            zero = np.zeros(len(LABELS))
            own = sum((self.model.own.get(f, zero) for f in key[0]), zero)
            # what this word adds to the word after it, and to the word before it
            self.rows.append((own, self.model.before.get(key[1], zero), self.model.after.get(key[1], zero)))
            self.types[key] = len(self.rows) - 1
        return self.types[key]

    def tag(self, lines: list[list[str]]) -> tuple[np.ndarray, np.ndarray]:
        """Label of each word of each line, one after the other with an edge before each line and at the end; and where lines begin."""
        if len(self.known) > CACHED_WORDS:
            self.known.clear()
        size = np.fromiter(map(len, lines), np.int64, len(lines))
        begins = np.cumsum(size + 1) - size
        ids = np.full(int(size.sum()) + len(lines) + 1, self.edge, np.int64)
        for b, words in zip(begins.tolist(), lines, strict=True):
            ids[b : b + len(words)] = np.fromiter(map(self.known.__getitem__, words), np.int64, len(words))
        own, before, after = (np.array([r[k] for r in self.rows]) for k in range(3))
        labels = np.zeros(len(ids), np.int64)
        # words that can be anything but O: decided once per triple of types
        m = len(self.rows)
        left, right = np.concatenate(([self.edge], ids[:-1])), np.concatenate((ids[1:], [self.edge]))
        gap = own[:, :1] - own - self.bound  # by type and label
        low_b, low_a = (before[:, :1] - before).min(axis=0), (after[:, :1] - after).min(axis=0)
        surely = ((gap + low_b + low_a)[:, 1:] > 0).all(axis=1)
        maybe = np.flatnonzero(~surely[ids])
        e = own[ids[maybe]] + before[left[maybe]] + after[right[maybe]]
        open_ = ((e[:, :1] - e - self.bound)[:, 1:] <= 0).any(axis=1)
        maybe, e = maybe[open_], e[open_]
        if len(maybe) and m:
            labels[maybe] = self.viterbi(maybe, e)
        return labels, begins

    def viterbi(self, at: np.ndarray, e: np.ndarray) -> np.ndarray:
        """Best labels of the runs of consecutive places in ``at``, O on either side of each."""
        moves = self.model.moves
        first = np.flatnonzero(np.concatenate(([True], np.diff(at) != 1)))
        size = np.diff(np.append(first, len(at)))
        order = np.argsort(-size, kind="stable")
        first, size = first[order], size[order]
        back = np.zeros((len(at), len(LABELS)), np.int8)
        score = moves[0] + e[first]
        last = np.empty(len(first), np.int64)
        for t in range(1, int(size[0]) + 1):
            live = int(np.searchsorted(-size, -t, side="left"))  # runs longer than t
            done = slice(live, len(score))
            last[done] = (score[done] + moves[:, 0]).argmax(axis=1)
            score = score[:live]
            if not live:
                break
            paths = score[:, :, None] + moves
            back[first[:live] + t] = paths.argmax(axis=1)
            score = paths.max(axis=1) + e[first[:live] + t]
        out = np.zeros(len(at), np.int64)
        now = last
        for t in range(int(size[0]) - 1, -1, -1):
            live = int(np.searchsorted(-size, -t, side="left"))
            out[first[:live] + t] = now[:live]
            now[:live] = back[first[:live] + t, now[:live]]
        return out


class _Shapes(dict):
    def __init__(self, tagger: Tagger):
        self.tagger = tagger

    def __missing__(self, word: str) -> int:
        plain = word if word.isalpha() else word[:-1]
        if plain.isalpha() and len(plain) < 25 and (plain is word or word[-1] in ",.") and plain.lower() not in _CUES:
            key = (("alpha", "cue="), "alpha")
        else:
            key = features(word)
        self[word] = found = self.tagger.type_of(key)
        return found


def field_spans(text: str, labels: np.ndarray) -> list[tuple[int, int, str]]:
    """Runs of one label other than O, without the punctuation around them."""
    found, open_ = [], None
    for m, label in zip(_WORD.finditer(text), labels.tolist(), strict=True):
        if label and open_ and open_[2] == label:
            open_[1] = m.end()
        elif label:
            open_ = [m.start(), m.end(), label]
            found.append(open_)
        else:
            open_ = None
    out = []
    for s, e, label in found:
        while s < e and text[s] in "\"'`,.;:!?[]{}<>|*#$%&=":
            s += 1
        while s < e and text[e - 1] in "\"'`,.;:!?[]{}<>|*#$%&=":
            e -= 1
        if s < e:
            out.append((s, e, LABELS[label]))
    return out


def find(texts: list[str | None], tagger: Tagger) -> list[tuple[list, list]]:
    """(pattern spans, all spans) of each text; a span of the field is added where no pattern span overlaps it."""
    lines = [_WORD.findall(t) if t else [] for t in texts]
    labels, begins = tagger.tag(lines)
    out = []
    for t, words, b in zip(texts, lines, begins.tolist(), strict=True):
        base = base_spans(t) if t else []
        mine = labels[b : b + len(words)]
        more = [x for x in field_spans(t, mine) if all(x[1] <= s or e <= x[0] for s, e, _ in base)] if mine.any() else []
        out.append((base, sorted(base + more, key=lambda x: (x[0], KINDS.index(x[2])))))
    return out


def written(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{kind}:{s}:{e}" for s, e, kind in spans)


def scan(docs: DataFrame, model: Field | None = None) -> DataFrame:
    """(doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans): one row per row of docs."""
    sent = docs.sparkSession.sparkContext.broadcast(model or fit(examples()))  # a few hundred weights

    def kernel(batches):
        tagger = Tagger(sent.value)
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                some = batch.slice(lo, 256)
                found = find(some.column("text").to_pylist(), tagger)
                counts = [pa.array([sum(x[2] == k for x in base) for base, _ in found], pa.int64()) for k in KINDS[:4]]
                digest = pa.array([hashlib.sha256(written(base).encode()).hexdigest() for base, _ in found], pa.string())
                yield pa.RecordBatch.from_arrays([some.column("doc_id"), *counts, digest, pa.array([written(every) for _, every in found], pa.string())], ["doc_id", *[f"n_{k}" for k in KINDS[:4]], "base_sha256", "spans"])

    rows = pick(docs, "doc_id", "text")
    return rows.mapInArrow(kernel, f"doc_id {dict(rows.dtypes)['doc_id']}, " + ", ".join(f"n_{k} long" for k in KINDS[:4]) + ", base_sha256 string, spans string")


def masked(docs: DataFrame, model: Field | None = None) -> DataFrame:
    """docs with every span replaced by its kind in angle brackets, all columns kept."""
    sent = docs.sparkSession.sparkContext.broadcast(model or fit(examples()))
    names = docs.columns
    at = names.index("text")
    pick(docs, "text")

    def kernel(batches):
        tagger = Tagger(sent.value)
        for batch in batches:
            texts = batch.column(at).to_pylist()
            for i, (_, spans) in enumerate(find(texts, tagger)):
                parts, end = [], 0
                for s, e, kind in spans:
                    if s >= end:
                        parts += [texts[i][end:s], f"<{kind}>"]
                        end = e
                texts[i] = "".join(parts) + texts[i][end:] if spans else texts[i]
            yield batch.set_column(at, batch.schema.field(at), pa.array(texts, batch.schema.field(at).type))

    plain = docs.toDF(*[f"_c{i}" for i in range(len(names))])
    return plain.mapInArrow(kernel, plain.schema).toDF(*names)
