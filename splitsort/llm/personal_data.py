"""Personal data: base patterns, and a linear-chain conditional random field that adds to them.

The base patterns are matched whole and linearly, whatever the text.  The CRF labels the tokens of
each line from features of their shapes; it is trained on a small labelled table by exact gradients
(forward-backward) and decoded by Viterbi over numpy batches of lines.  Lines of which it can be proved
from the margins of their tokens that the all-outside path is best are not decoded step by step.
The spans it adds are those it labels and no base span of the same kind touches.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import released, small_batches, widened

KINDS = ("email", "ip", "card", "phone")
#: B- and I- for each kind, O first.
LABELS = ("O", *(f"{p}-{k}" for k in KINDS for p in "BI"))

EMAIL_LEFT, EMAIL_RIGHT = re.compile(r"[A-Za-z0-9._%+-]+\Z"), re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)+")
IP = re.compile(r"(?<![0-9])([0-9]++)\.([0-9]++)\.([0-9]++)\.([0-9]++)")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DIGIT = re.compile(r"[0-9]")
_DOUBLED = (0, 2, 4, 6, 8, 1, 3, 5, 7, 9)


def luhn(digits: str) -> bool:
    return sum(_DOUBLED[int(d)] if k % 2 else int(d) for k, d in enumerate(reversed(digits))) % 10 == 0


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """``(start, end, kind)`` in code points of what the base patterns find and their checks accept."""
    out = []
    at, end = text.find("@"), 0
    while at >= 0:  # every address has one @; what precedes it is cut at the last accepted or matched end
        left = at
        while left > end and text[left - 1] in LOCAL:
            left -= 1
        m = EMAIL_RIGHT.match(text, at + 1) if left < at else None
        if m:
            out.append((left, m.end(), "email"))
        end = m.end() if m else at + 1
        at = text.find("@", at + 1)
    if not DIGIT.search(text):
        return out
    for m in IP.finditer(text):
        if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or "0") <= 255 for p in m.groups()):
            out.append((m.start(), m.end(), "ip"))
    for m in CARD.finditer(text):
        if m.end() - m.start() <= 37:
            digits = m.group().replace(" ", "").replace("-", "")
            if 12 <= len(digits) <= 19 and luhn(digits):
                out.append((m.start(), m.end(), "card"))
    if "+" in text:
        for m in PHONE.finditer(text):
            if 9 <= len(DIGIT.findall(m.group())) <= 15:
                out.append((m.start(), m.end(), "phone"))
    return out


# --- the conditional random field ---

TOKEN = re.compile(r"\S+")
TRIM = "\"'<>[]{}*#%&$!?,;:|"
#: An address with its signs spelt out between brackets, as some write them.
SPELT = re.compile(r"[(\[{](?:at|dot)[)\]}]")


def shape(token: str) -> str:
    """Letters to a or A, digits to 9, runs shortened to one with a length class for digits."""
    s = re.sub(r"[^\W\d_A-Z]+", "a", re.sub(r"[A-Z]+", "A", token))
    return re.sub(r"\d+", lambda m: "9" * min(len(m.group()), 4) if len(m.group()) < 12 else "9L", s)


def token_features(token: str) -> list[str]:
    """Features of one token's shape."""
    core = token.strip(TRIM)
    s = shape(core)
    digits = sum(c.isdigit() for c in core)
    out = ["bias", f"shape={s[:24]}", f"first={s[:1]}", f"last={s[-1:]}", f"digits={min(digits, 20)}"]
    out += [f"has{c}" for c in "@.+-()/:" if c in core]
    if core.count(".") == 3 and digits:
        parts = core.split(".")
        out.append("quad" if all(p.isdigit() and len(p) <= 3 and int(p) <= 255 for p in parts) else "badquad")
    if "@" in core:
        out.append("dotted" if re.search(r"@[\w-]+(\.[\w-]+)+$", core) else "undotted")
    if digits >= 12 and digits + core.count("-") + core.count(".") == len(core):
        out.append("luhn" if digits <= 19 and luhn(core.replace("-", "").replace(".", "")) else "noluhn")
    if SPELT.search(token):
        out.append("spelt")
    if core.isalpha():
        out.append("word")
    return out


def labelled_table(n: int = 320, seed: int = 3) -> list[tuple[list[str], list[str]]]:
    """The small labelled table: token sequences made by rule, with their labels.

    Personal data in several notations among plain words, beside numbers, versions, hashes, prices and
    dates that are none.
    """
    rng = np.random.default_rng(seed)
    d = lambda k: "".join(map(str, rng.integers(0, 10, k)))
    w = lambda: "".join(rng.choice(list("aeinorstlhdcu"), rng.integers(2, 9)))

    def card(groups: tuple[int, ...], sep: str, good: bool = True) -> str:
        body = str(rng.integers(3, 7)) + d(sum(groups) - 2)
        digits = next(body + c for c in "0123456789" if luhn(body + c) == good)
        cut = np.cumsum((0, *groups))
        return sep.join(digits[a:b] for a, b in zip(cut, cut[1:], strict=False))

    def quad(top: int = 256) -> str:
        return ".".join(str(x) for x in rng.integers(1, top, 4))

    makers = [
        ("email", lambda: f"{w()}.{w()}@{w()}.com"), ("email", lambda: f"{w()}{d(2)}@{w()}.example.org"), ("email", lambda: f"{w()}_{w()}@mail.{w()}.net"),
        ("ip", quad), ("card", lambda: card((16,), "")), ("card", lambda: card((4, 4, 4, 4), " ")), ("card", lambda: card((4, 4, 4, 4), "-")), ("card", lambda: card((4, 6, 5), " ")),
        ("phone", lambda: f"+{d(1)} ({d(3)}) {d(3)}-{d(4)}"), ("phone", lambda: f"+{d(2)} {d(3)} {d(3)} {d(4)}"), ("phone", lambda: f"+{d(11)}"),
        ("phone", lambda: f"({d(3)}) {d(3)}-{d(4)}"), ("phone", lambda: f"{d(3)}-{d(3)}-{d(4)}"), ("phone", lambda: f"{d(3)}.{d(3)}.{d(4)}"),
        ("email", lambda: f"{w()}.{w()} (at) {w()}.com"), ("email", lambda: f"{w()} [at] {w()} [dot] org"), ("email", lambda: f"{w()}{d(2)}(at){w()}(dot)net"), ("card", lambda: card((4, 4, 4, 4), ".")),
    ]
    decoys = [
        lambda: d(int(rng.integers(1, 8))), lambda: f"{d(1)}.{d(2)}", lambda: f"v{d(1)}.{d(1)}.{d(1)}", lambda: f"{d(4)}-{d(2)}-{d(2)}", lambda: f"${d(3)}.{d(2)}",
        lambda: "".join(rng.choice(list("0123456789abcdef"), 40)), lambda: quad(256) + "." + d(2), lambda: ".".join(str(x) for x in rng.integers(256, 999, 4)),
        lambda: card((16,), "", False), lambda: card((4, 4, 4, 4), "-", False), lambda: card((4, 4, 4, 4), ".", False), lambda: f"{d(3)}.{d(3)}", lambda: f"({w()})", lambda: f"[{w()}]", lambda: "at", lambda: "dot", lambda: f"@{w()}", lambda: f"{w()}@{w()}", lambda: f"{d(2)}:{d(2)}", lambda: f"{d(3)}-{d(4)}", lambda: f"{d(1)}/{d(1)}", lambda: f"({d(4)})", lambda: f"+{d(2)}", lambda: f"({w()})", lambda: f"{w()}-{w()}", lambda: f"{w()}.{w()}",
    ]
    tails = ["", "", "", "", ",", ".", "!!", "***", "%%%", "$$$", "###", "&&&"]
    table = []
    for k in range(n):
        tokens: list[str] = []
        labels: list[str] = []
        for _ in range(int(rng.integers(2, 6))):
            plain = [w() + str(rng.choice(["", "", ",", "."])) for _ in range(int(rng.integers(1, 6)))]
            plain = [p.capitalize() if rng.random() < 0.2 else p.upper() if rng.random() < 0.1 else p for p in plain]
            tokens, labels = tokens + plain, labels + ["O"] * len(plain)
            if rng.random() < 0.5:
                kind, make = makers[int(rng.integers(len(makers)))]
                parts = make().split(" ")
                tokens += [*parts[:-1], parts[-1] + str(rng.choice(tails))]
                labels += [f"B-{kind}", *[f"I-{kind}"] * (len(parts) - 1)]
            else:
                tokens.append(decoys[int(rng.integers(len(decoys)))]() + str(rng.choice(tails)))
                labels.append("O")
        table.append((tokens, labels))
    return table


@dataclass(frozen=True)
class Crf:
    """Weights by feature for the token itself and its two neighbours, and between labels."""

    index: dict[str, int]
    emit: np.ndarray  # 3 x features x labels: previous, own, next token's features
    move: np.ndarray  # labels x labels
    start: np.ndarray

    def scores(self, token: str) -> np.ndarray:
        """3 x labels: what this token adds to its successor's, its own and its predecessor's labels."""
        rows = [self.index[f] for f in token_features(token) if f in self.index]
        return self.emit[:, rows, :].sum(axis=1)


@lru_cache(1)
def default_crf() -> Crf:
    """The model fitted to the labelled table, once a process."""
    return train(labelled_table())


def _lse(x: np.ndarray, axis: int) -> np.ndarray:
    m = x.max(axis=axis, keepdims=True)
    return (m + np.log(np.exp(x - m).sum(axis=axis, keepdims=True))).squeeze(axis)


def train(table: list[tuple[list[str], list[str]]], steps: int = 40, l2: float = 0.02) -> Crf:
    """Maximum likelihood with an L2 penalty, by Adam on exact gradients of the whole table at once."""
    feats = [[token_features(t) for t in tokens] for tokens, _ in table]
    index: dict[str, int] = {}
    for f in (f for seq in feats for tok in seq for f in tok):
        index.setdefault(f, len(index))
    size, longest, n = len(LABELS), max(len(t) for t, _ in table), len(table)
    x = np.zeros((n, longest, len(index)), np.float32)
    y, mask = np.zeros((n, longest), np.int64), np.zeros((n, longest), np.float32)
    for i, (seq, (_, labels)) in enumerate(zip(feats, table, strict=True)):
        for t, tok in enumerate(seq):
            x[i, t, [index[f] for f in tok]] = 1
            y[i, t], mask[i, t] = LABELS.index(labels[t]), 1
    zero = np.zeros((n, 1, len(index)), np.float32)
    views = [np.concatenate([zero, x[:, :-1]], 1), x, np.concatenate([x[:, 1:], zero], 1)]
    flat = np.concatenate(views, axis=2).reshape(n * longest, -1)
    params = {"emit": np.zeros((flat.shape[1], size)), "move": np.zeros((size, size)), "start": np.zeros(size)}
    first, second = ({k: np.zeros_like(v) for k, v in params.items()} for _ in range(2))
    gold = np.eye(size)[y] * mask[..., None]
    pairs = np.einsum("nta,ntb->ab", gold[:, :-1], gold[:, 1:])
    for k in range(1, steps + 1):
        e = (flat @ params["emit"].astype(np.float32)).reshape(n, longest, size).astype(np.float64)
        a, b = np.zeros_like(e), np.zeros_like(e)
        a[:, 0] = params["start"] + e[:, 0]
        for t in range(1, longest):
            step = _lse(a[:, t - 1, :, None] + params["move"], 1) + e[:, t]
            a[:, t] = np.where(mask[:, t, None] > 0, step, a[:, t - 1])
        z = _lse(a[:, -1], 1)
        for t in range(longest - 2, -1, -1):
            step = _lse(params["move"] + (e[:, t + 1] + b[:, t + 1])[:, None, :], 2)
            b[:, t] = np.where(mask[:, t + 1, None] > 0, step, 0.0)
        post = np.exp(a + b - z[:, None, None]) * mask[..., None]
        expect = np.zeros((size, size))
        for t in range(longest - 1):
            joint = a[:, t, :, None] + params["move"] + (e[:, t + 1] + b[:, t + 1])[:, None, :] - z[:, None, None]
            expect += (np.exp(np.minimum(joint, 0)) * mask[:, t + 1, None, None]).sum(0)
        grads = {
            "emit": flat.T @ (post - gold).reshape(n * longest, size).astype(np.float32) / n + l2 * params["emit"] / 10,
            "move": (expect - pairs) / n + l2 * params["move"] / 10,
            "start": (post[:, 0] - gold[:, 0]).sum(0) / n,
        }
        for name, g in grads.items():
            first[name] = 0.9 * first[name] + 0.1 * g
            second[name] = 0.99 * second[name] + 0.01 * g * g
            params[name] = params[name] - 0.3 * (first[name] / (1 - 0.9**k)) / (np.sqrt(second[name] / (1 - 0.99**k)) + 1e-8)
    return Crf(index, params["emit"].reshape(3, len(index), size), params["move"], params["start"])


def viterbi(emit: np.ndarray, lengths: np.ndarray, move: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Best labels of a batch of padded sequences (batch x time x labels); beyond a length they are 0."""
    n, longest, size = emit.shape
    best, back = start + emit[:, 0], np.zeros((n, longest, size), np.int8)
    ends = np.zeros((n, size))
    ends[lengths == 1] = best[lengths == 1]
    for t in range(1, longest):
        way = best[:, :, None] + move
        back[:, t] = way.argmax(axis=1)
        best = way.max(axis=1) + emit[:, t]
        ends[lengths == t + 1] = best[lengths == t + 1]
    out = np.zeros((n, longest), np.int8)
    rows = np.arange(n)
    label = ends.argmax(axis=1)
    for t in range(longest - 1, -1, -1):
        here = lengths > t
        label = np.where(lengths - 1 == t, ends.argmax(axis=1), label)
        out[here, t] = label[here]
        label = np.where(here & (lengths - 1 >= t), back[rows, t, label], label)
    return out


class Tagger:
    """Decodes whole texts with one CRF; types of tokens are remembered, within a bound."""

    REMEMBERED, BATCH = 400_000, 256

    def __init__(self, crf: Crf) -> None:
        self.crf, self.kinds, self.ids = crf, {}, {}
        self.table = np.zeros((1024, 3, len(LABELS)))
        rest = crf.move - crf.move[0, 0]
        enter = max(rest[0, 1:].max(), (crf.start[1:] - crf.start[0]).max())
        leave, stay = max(rest[1:, 0].max(), 0.0), rest[1:, 1:].max()
        # Leaving O for m tokens gains at most enter + leave + (m - 1) * stay, so m times this at most.
        self.slack = max(enter + leave, stay, enter, 0.0)

    @staticmethod
    def stand_in(token: str) -> str:
        """A short token with the same features: plain words have only a few kinds."""
        body = token.rstrip(".,")
        tail = token[len(body) :]
        if len(tail) < 2 and body.isalpha():
            if body.islower():
                return "a" + tail
            if "A" <= body[0] <= "Z" and (len(body) == 1 or body[1:].islower()):
                return ("A" if len(body) == 1 else "Aa") + tail
        return token

    def kind(self, token: str) -> int:
        """The row of this token's scores; new tokens get one by their stand-in."""
        own = self.stand_in(token)
        k = self.kinds.get(own)
        if k is None:
            k = self.kinds[own] = len(self.kinds)
            if k >= len(self.table):
                self.table = np.concatenate([self.table, np.zeros_like(self.table)])
            self.table[k] = self.crf.scores(own)
        self.ids[token] = k
        return k

    def types(self, tokens: list[str]) -> np.ndarray:
        get = self.ids.get
        found = [get(t, -1) for t in tokens]
        return np.array([k if k >= 0 else self.kind(t) for k, t in zip(found, tokens, strict=True)] if -1 in found else found)

    def lines(self, text: str) -> list[tuple[int, list[tuple[int, int]], np.ndarray]]:
        """Of each line that can't be proved free: its tokens' places and their emission scores."""
        out, at = [], 0
        for line in text.split("\n"):
            tokens = line.split()
            if tokens:
                kinds = self.types(tokens)
                s = self.table[kinds]
                e = s[:, 1].copy()
                e[1:] += s[:-1, 0]
                e[:-1] += s[1:, 2]
                if (e[:, 1:].max(axis=1) + self.slack >= e[:, 0]).any():
                    out.append((at, [m.span() for m in TOKEN.finditer(line)], e))
            at += len(line) + 1
        if len(self.ids) > self.REMEMBERED:
            self.ids.clear()
            self.kinds.clear()
        return out

    def tag(self, texts: list[str]) -> list[list[tuple[int, int, str]]]:
        """CRF spans of each text."""
        found: list[list[tuple[int, int, str]]] = [[] for _ in texts]
        todo = [(i, *line) for i, text in enumerate(texts) for line in self.lines(text)]
        todo.sort(key=lambda x: len(x[2]))
        k = 0
        while k < len(todo):
            some = [todo[k]]
            while k + len(some) < len(todo) and len(some) < self.BATCH and (len(some) + 1) * len(todo[k + len(some)][2]) <= 200_000:
                some.append(todo[k + len(some)])
            k += len(some)
            lengths = np.array([len(x[2]) for x in some])
            emit = np.zeros((len(some), lengths.max(), len(LABELS)))
            for j, x in enumerate(some):
                emit[j, : lengths[j]] = x[3]
            for (i, at, places, _), labels in zip(some, viterbi(emit, lengths, self.crf.move, self.crf.start), strict=True):
                hits = np.flatnonzero(labels[: len(places)])
                j = 0
                while j < len(hits):
                    a = z = int(hits[j])
                    kind = LABELS[labels[a]][2:]
                    while j + 1 < len(hits) and hits[j + 1] == z + 1 and LABELS[labels[z + 1]] == f"I-{kind}":
                        z, j = z + 1, j + 1
                    j += 1
                    start, end = at + places[a][0], at + places[z][1]
                    span = texts[i][start:end]
                    start += len(span) - len(span.lstrip(TRIM + "."))
                    end -= len(span) - len(span.rstrip(TRIM + "."))
                    if start < end:
                        found[i].append((start, end, kind))
        return found


def _plausible(text: str, span: tuple[int, int, str]) -> bool:
    """A label sequence is only kept if its text can be of the kind at all."""
    s, digits = text[span[0] : span[1]], sum(c in "0123456789" for c in text[span[0] : span[1]])
    if span[2] == "email":
        return "@" in s or "at" in (m.group()[1:-1] for m in SPELT.finditer(s))
    if span[2] == "phone":
        return 9 <= digits <= 15 and not any(c.isalpha() for c in s)
    if span[2] == "card":
        d = re.sub(r"[ .-]", "", s)
        return d.isascii() and d.isdigit() and 12 <= len(d) <= 19 and luhn(d)
    return s.count(".") == 3 and all(p.isascii() and p.isdigit() and int(p) <= 255 for p in s.split(".") if len(p) <= 3) and all(0 < len(p) <= 3 for p in s.split("."))


def all_spans(text: str, base: list[tuple[int, int, str]], extra: list[tuple[int, int, str]]) -> list[tuple[int, int, str]]:
    """Base spans and those of ``extra`` that are plausible and meet no base span, in order."""
    out = list(base)
    for s in extra:
        if _plausible(text, s) and not any(s[0] < b[1] and b[0] < s[1] for b in base):
            out.append(s)
    return sorted(out, key=lambda s: (s[0], KINDS.index(s[2]), s[1]))


def listed(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in spans)


def find(docs: DataFrame, crf: Crf, text: str = "text") -> DataFrame:
    """All rows and columns of ``docs`` with counts, ``base_sha256`` and ``spans``.

    Whole texts; null counts as empty.  ``n_email n_ip n_card n_phone`` count base spans; ``base_sha256``
    is the digest of the base list, ``spans`` lists base and added spans as kind:start:end by start,
    then kind.  Columns of the input with these names are replaced.  No shuffle; the model (a few hundred
    rows of weights) travels with the function.
    """
    new = [f"n_{k}" for k in KINDS] + ["base_sha256", "spans"]
    docs = docs.drop(*new)
    small_batches(docs.sparkSession)
    at, names = docs.columns.index(text), docs.columns
    schema = widened(docs, **{c: "long" if c.startswith("n_") else "string" for c in new})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tagger = Tagger(crf)
        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                part = batch.slice(lo, 500)
                texts = [t or "" for t in part.column(at).to_pylist()]
                rows = []
                for t, extra in zip(texts, tagger.tag(texts), strict=True):
                    base = sorted(base_spans(t), key=lambda s: (s[0], KINDS.index(s[2])))
                    counts = [sum(s[2] == k for s in base) for k in KINDS]
                    rows.append((*counts, hashlib.sha256(listed(base).encode()).hexdigest(), listed(all_spans(t, base, extra))))
                cols = [pa.array([r[k] for r in rows], pa.int64() if k < len(KINDS) else pa.string()) for k in range(len(new))]
                yield pa.RecordBatch.from_arrays([*part.columns, *cols], [*names, *new])

    return docs.mapInArrow(lambda b: released(run(b)), schema)


def redact(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` as ``find`` returns it, each span of the text replaced by its kind in brackets."""
    names = docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for t, spans in zip(batch.column(names.index(text)).to_pylist(), batch.column(names.index("spans")).to_pylist(), strict=True):
                last = len(t or "")
                for kind, a, b in reversed([s.split(":") for s in (spans or "").split(",") if s]):
                    if int(b) <= last:
                        t, last = f"{t[: int(a)]}[{kind}]{t[int(b) :]}", int(a)
                out.append(t)
            cols = list(batch.columns)
            cols[names.index(text)] = pa.array(out, pa.string())
            yield pa.RecordBatch.from_arrays(cols, names)

    return docs.mapInArrow(run, docs.schema)


def labelled_frame(spark: SparkSession) -> DataFrame:
    """The labelled table as a DataFrame, for users who extend it."""
    return spark.createDataFrame([{"tokens": t, "labels": v} for t, v in labelled_table()], "tokens array<string>, labels array<string>")
