"""Personal data: exact patterns, and a character-level bidirectional LSTM with CRF transitions that adds spans.

The patterns give emails, IPv4 addresses, payment cards (Luhn) and international phone numbers. The tagger is trained in
numpy on labelled spans: pattern matches in a bounded sample of documents (SAMPLE_DOCS, TRAIN_WINDOWS), and rewritten forms of
them that the patterns miss (no country code, other separators, spaces around the at sign). It reads overlapping windows; where
windows overlap a character's scores are averaged by how central it is, and one Viterbi pass runs over each joined stretch, so a
span that crosses windows is decoded once, however long the stretch.

A tagged span counts only if it holds a digit or an at sign, passes its kind's check, and meets no pattern match. So the tagger
reads the windows with a digit or an at sign and MARGIN more on either side; a tagged span that reaches further than those from
every digit and at sign would be cut there.

Nulls: a null text is empty. Repeated rows stay; extra columns are ignored; without labelled spans only patterns are used. Long
texts are tagged in bounded batches of windows. Offsets are code points, ends exclusive.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .base import give_back

KINDS = ["email", "ip", "card", "phone"]
TAGS = 1 + 2 * len(KINDS)  # O, then begin and inside of each kind

# The patterns that the base spans follow. The digit look-behind only saves time: a match never starts inside a run of digits.
IP = re.compile(r"(?<![0-9])[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")

SAMPLE_DOCS = 20_000  # documents looked at for labelled spans, in expectation at most
TRAIN_WINDOWS = 3000
FORMS = 2  # rewritten forms of each labelled span
STEPS = 500  # of training, in batches of 64 windows
OTHERS = 40  # one in so many digits and at signs outside spans is an example too, drawn by hash
WINDOW, STRIDE = 64, 32
MARGIN = 1  # windows read beyond those with a digit or an at sign
PART = 1024  # windows computed at once
EMBED, HIDDEN = 12, 16


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 if d > 9 else d
    return total % 10 == 0


def only_digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def valid(kind: str, s: str) -> bool:
    if kind == "email":
        return "@" in s
    if kind == "ip":
        return all(len(p) <= 3 and int(p or "0") <= 255 for p in (x.lstrip("0") for x in s.split(".")))
    n = only_digits(s)
    return 12 <= len(n) <= 19 and luhn(n) if kind == "card" else 9 <= len(n) <= 15


def emails(text: str) -> Iterator[tuple[int, int]]:
    """Leftmost matches, found from their at signs so that long runs of letters cost nothing."""
    free, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > free and text[start - 1] in LOCAL:
            start -= 1
        m = DOMAIN.match(text, at + 1) if start < at else None
        if m:
            yield start, m.end()
            free = m.end()
        at = text.find("@", max(at + 1, free))


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end), sorted."""
    out = [(a, 0, b) for a, b in emails(text)] if "@" in text else []
    for kind, pattern in ((1, IP), (2, CARD), (3, PHONE)):
        if kind != 3 or "+" in text:
            out += [(m.start(), kind, m.end()) for m in pattern.finditer(text) if valid(KINDS[kind], m[0])]
    return sorted(out)


def show(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


ANCHOR = re.compile(r"[0-9@]")

# Characters as the tagger sees them: digits are one class, letters three (lower, upper, other), and marks their own.
_MARKS = "@.+-() _/:;,=#[]{}<>'\"\n"
CLASSES = 5 + len(_MARKS) + 26


def _class_table() -> np.ndarray:
    t = np.full(128, 4, np.int16)
    for i, c in enumerate(_MARKS):
        t[ord(c)] = 5 + i
    for i in range(26):
        t[97 + i] = 5 + len(_MARKS) + i
        t[65 + i] = 1
    t[48:58] = 0
    return t


_CLASS = _class_table()


def classes(text: str) -> np.ndarray:
    x = np.frombuffer(text.encode("utf-32-le"), np.uint32)
    return np.where(x < 128, _CLASS[np.minimum(x, 127)], 2).astype(np.int16)


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-x))


class Tagger:
    def __init__(self, seed: int = 5):
        rng = np.random.default_rng(seed)
        f = lambda *s: (rng.standard_normal(s) / np.sqrt(s[0])).astype(np.float32)
        self.p = {"emb": f(CLASSES + 1, EMBED), "out": f(2 * HIDDEN, TAGS), "bias": np.zeros(TAGS, np.float32), "trans": np.zeros((TAGS, TAGS), np.float32)}
        for d in "fb":
            self.p |= {d + "x": f(EMBED, 4 * HIDDEN), d + "h": f(HIDDEN, 4 * HIDDEN), d + "b": np.zeros(4 * HIDDEN, np.float32)}
            self.p[d + "b"][HIDDEN : 2 * HIDDEN] = 1  # gates are input, forget, output, candidate

    def _direction(self, x: np.ndarray, d: str, keep: list | None = None) -> np.ndarray:
        B, T, _ = x.shape
        H = HIDDEN
        pre = x @ self.p[d + "x"] + self.p[d + "b"]
        h, c = np.zeros((B, H), np.float32), np.zeros((B, H), np.float32)
        out = np.empty((B, T, H), np.float32)
        for t in range(T) if d == "f" else range(T - 1, -1, -1):
            z = pre[:, t] + h @ self.p[d + "h"]
            gates, cand = _sigmoid(z[:, : 3 * H]), np.tanh(z[:, 3 * H :])
            c0, h0 = c, h
            c = gates[:, H : 2 * H] * c0 + gates[:, :H] * cand
            tc = np.tanh(c)
            h = gates[:, 2 * H :] * tc
            out[:, t] = h
            if keep is not None:
                keep.append((t, gates, cand, c0, h0, tc))
        return out

    def emissions(self, codes: np.ndarray) -> np.ndarray:
        """codes [B, T] (CLASSES pads) -> scores [B, T, TAGS]."""
        x = self.p["emb"][codes]
        return np.concatenate([self._direction(x, "f"), self._direction(x, "b")], axis=2) @ self.p["out"] + self.p["bias"]

    def _backward(self, d: str, x: np.ndarray, grad: np.ndarray, kept: list, g: dict) -> np.ndarray:
        H = HIDDEN
        dh, dc = np.zeros_like(grad[:, 0]), np.zeros_like(grad[:, 0])
        dx = np.zeros_like(x)
        for t, gates, cand, c0, h0, tc in reversed(kept):
            dh = dh + grad[:, t]
            i, f, o = gates[:, :H], gates[:, H : 2 * H], gates[:, 2 * H :]
            dc = dc + dh * o * (1 - tc**2)
            dz = np.concatenate([dc * cand * i * (1 - i), dc * c0 * f * (1 - f), dh * tc * o * (1 - o), dc * i * (1 - cand**2)], axis=1)
            g[d + "x"] += x[:, t].T @ dz
            g[d + "h"] += h0.T @ dz
            g[d + "b"] += dz.sum(0)
            dx[:, t] = dz @ self.p[d + "x"].T
            dh, dc = dz @ self.p[d + "h"].T, dc * f
        return dx

    def step(self, codes: np.ndarray, tags: np.ndarray) -> tuple[float, dict]:
        """Mean negative log likelihood of the tag sequences under the CRF, and its gradients."""
        B, T = codes.shape
        x = self.p["emb"][codes]
        kf: list = []
        kb: list = []
        hidden = np.concatenate([self._direction(x, "f", kf), self._direction(x, "b", kb)], axis=2)
        e = (hidden @ self.p["out"] + self.p["bias"]).astype(np.float64)
        tr = self.p["trans"].astype(np.float64)
        alpha, beta = np.zeros((T, B, TAGS)), np.zeros((T, B, TAGS))
        alpha[0] = e[:, 0]
        lse = lambda v, axis: (m := v.max(axis=axis, keepdims=True)).squeeze(axis) + np.log(np.exp(v - m).sum(axis=axis))
        for t in range(1, T):
            alpha[t] = lse(alpha[t - 1][:, :, None] + tr, 1) + e[:, t]
        for t in range(T - 2, -1, -1):
            beta[t] = lse(tr + (e[:, t + 1] + beta[t + 1])[:, None, :], 2)
        z = lse(alpha[-1], 1)
        rows = np.arange(B)
        gold = e[rows[:, None], np.arange(T), tags].sum(1) + tr[tags[:, :-1], tags[:, 1:]].sum(1)
        de = np.exp(alpha + beta - z[None, :, None]).transpose(1, 0, 2)
        np.subtract.at(de, (rows[:, None], np.arange(T), tags), 1)
        dtr = np.zeros_like(tr)
        for t in range(T - 1):
            dtr += np.exp(alpha[t][:, :, None] + tr + (e[:, t + 1] + beta[t + 1])[:, None, :] - z[:, None, None]).sum(0)
        np.subtract.at(dtr, (tags[:, :-1].ravel(), tags[:, 1:].ravel()), 1)
        de = (de / B).astype(np.float32)
        g = {k: np.zeros_like(v) for k, v in self.p.items()}
        g["trans"] = (dtr / B).astype(np.float32)
        g["bias"] = de.sum((0, 1))
        g["out"] = hidden.reshape(-1, 2 * HIDDEN).T @ de.reshape(-1, TAGS)
        dh = de @ self.p["out"].T
        dx = self._backward("f", x, dh[:, :, :HIDDEN], kf, g) + self._backward("b", x, dh[:, :, HIDDEN:], kb, g)
        np.add.at(g["emb"], codes, dx)
        return float((z - gold).mean()), g

    def train(self, codes: np.ndarray, tags: np.ndarray, epochs: int = 8, batch: int = 64, rate: float = 0.01, seed: int = 11) -> list[float]:
        rng = np.random.default_rng(seed)
        m, v, n, losses = {k: 0.0 for k in self.p}, {k: 0.0 for k in self.p}, 0, []
        for epoch in range(epochs):
            total = 0.0
            order = rng.permutation(len(codes))
            for i in range(0, len(order), batch):
                loss, g = self.step(codes[order[i : i + batch]], tags[order[i : i + batch]])
                total += loss * len(order[i : i + batch])
                n += 1
                scale = min(1.0, 5.0 / (np.sqrt(sum(float((x**2).sum()) for x in g.values())) + 1e-9))
                for k, x in g.items():
                    x = x * scale
                    m[k], v[k] = 0.9 * m[k] + 0.1 * x, 0.999 * v[k] + 0.001 * x**2
                    self.p[k] = (self.p[k] - rate * (1 - epoch / epochs) * (m[k] / (1 - 0.9**n)) / (np.sqrt(v[k] / (1 - 0.999**n)) + 1e-8)).astype(np.float32)
            losses.append(total / max(len(codes), 1))
        return losses

    def viterbi(self, parts: Iterator[np.ndarray]) -> np.ndarray:
        """Best tags of one stretch, whose scores [T, TAGS] come in parts; an inside tag follows its own kind only."""
        allowed = np.zeros((TAGS, TAGS), np.float32)
        for k in range(len(KINDS)):
            bad = [t for t in range(TAGS) if t not in (1 + 2 * k, 2 + 2 * k)]
            allowed[bad, 2 + 2 * k] = -1e9
        tr = self.p["trans"] + allowed
        score, backs = None, []
        for e in parts:
            back = np.zeros(e.shape, np.int8)
            for t in range(len(e)):
                if score is None:
                    score = e[0].copy()
                    score[2::2] = -1e9
                    continue
                s = score[:, None] + tr
                back[t] = s.argmax(0)
                score = s.max(0) + e[t]
            score = score - score.max()
            backs.append(back)
        back = np.concatenate(backs)
        tags = np.empty(len(back), np.int8)
        tags[-1] = score.argmax()
        for t in range(len(back) - 1, 0, -1):
            tags[t - 1] = back[t, tags[t]]
        return tags

    def _scores(self, codes: np.ndarray, run: np.ndarray) -> Iterator[np.ndarray]:
        """Scores of the characters under a run of windows, in parts; what later windows add to is carried on."""
        start, end = int(run[0]) * STRIDE, min(int(run[-1]) * STRIDE + WINDOW, len(codes))
        weight = np.minimum(np.arange(WINDOW) + 1, WINDOW - np.arange(WINDOW)).astype(np.float32)
        left, done = np.zeros((0, TAGS + 1), np.float32), 0
        for first in range(0, len(run), PART):
            part = run[first : first + PART]
            at = part[:, None] * STRIDE + np.arange(WINDOW)
            e = self.emissions(np.where(at < len(codes), codes[np.minimum(at, len(codes) - 1)], CLASSES))
            total = np.zeros(((len(part) - 1) * STRIDE + WINDOW, TAGS + 1), np.float32)  # the last column sums weights
            total[: len(left)] += left
            for w in range(len(part)):
                total[w * STRIDE : w * STRIDE + WINDOW, :TAGS] += e[w] * weight[:, None]
                total[w * STRIDE : w * STRIDE + WINDOW, TAGS] += weight
            ready = len(part) * STRIDE if first + PART < len(run) else end - start - done
            yield total[:ready, :TAGS] / total[:ready, TAGS:]
            left, done = total[ready:], done + ready

    def stretches(self, codes: np.ndarray, anchors: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
        """Tags of the joined windows around anchors: (start, tags)."""
        last = max(0, -(-(len(codes) - WINDOW) // STRIDE))
        lo, hi = np.maximum(0, -(-(anchors - WINDOW + 1) // STRIDE) - MARGIN), np.minimum(anchors // STRIDE + MARGIN, last)
        edge = np.zeros(last + 2, np.int64)
        np.add.at(edge, lo, 1)
        np.add.at(edge, hi + 1, -1)
        numbers = np.flatnonzero(np.cumsum(edge[:-1]) > 0)
        for run in np.split(numbers, np.flatnonzero(np.diff(numbers) > 1) + 1):
            yield int(run[0]) * STRIDE, self.viterbi(self._scores(codes, run))

    def spans(self, text: str, base: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
        anchors = np.array([m.start() for m in ANCHOR.finditer(text)], np.int64)
        if not len(anchors):
            return []
        taken = sorted((a, b) for a, _, b in base)
        out = []
        for start, tags in self.stretches(classes(text), anchors):
            opens = np.flatnonzero((tags % 2 == 1))
            for a in opens.tolist():
                b = a + 1
                while b < len(tags) and tags[b] == tags[a] + 1:
                    b += 1
                s, kind = text[start + a : start + b], (tags[a] - 1) // 2
                span = (start + a, int(kind), start + b)
                if ANCHOR.search(s) and s.strip() == s and added_valid(KINDS[kind], s) and not any(x < span[2] and span[0] < y for x, y in taken):
                    out.append(span)
        return out


def added_valid(kind: str, s: str) -> bool:
    """Checks of tagged spans, at least as strict as those of the patterns where both apply."""
    if kind == "email":
        return re.fullmatch(r"[A-Za-z0-9._%+-]+ ?@ ?[A-Za-z0-9-]+( ?\. ?[A-Za-z0-9-]+)+", s) is not None
    if kind == "ip":
        return re.fullmatch(r"[0-9]{1,3}( ?\. ?[0-9]{1,3}){3}", s) is not None and all(int(p) <= 255 for p in s.replace(" ", "").split("."))
    if kind == "card":
        return re.fullmatch(r"[0-9]([\x20./-]?[0-9])+", s) is not None and valid(kind, s)
    return re.fullmatch(r"[(+]?[0-9][\x20()./0-9-]+[0-9]", s) is not None and any(c in s for c in " ()./-") and 9 <= len(only_digits(s)) <= 15


def rewritten(kind: int, s: str, rng: np.random.Generator) -> str:
    """A form of a labelled span that the patterns may miss."""
    r = int(rng.integers(3))
    if kind == 0:
        return s.replace("@", [" @ ", "@ ", " @"][r])
    if kind == 1:
        return s.replace(".", [" . ", " .", ". "][r])
    d = only_digits(s)
    if kind == 2:
        return [".", "/", ". "][r][:1].join(d[i : i + 4] for i in range(0, len(d), 4))
    d = d[-10:]
    return [f"({d[:3]}) {d[3:6]}-{d[6:]}", f"{d[:3]}-{d[3:6]}-{d[6:]}", f"{d[:3]}.{d[3:6]}.{d[6:]}"][r]


#: A stretch of text around a span or another anchor: kind (-1: no span), text, where it starts there, and all spans in it.
EXAMPLE = "kind int, part string, near int, spans array<struct<a:int,k:int,b:int>>"


def stretches_of(text: str) -> Iterator[tuple[int, str, int, list[dict]]]:
    """EXAMPLE rows of a text: one for every pattern match, and one in OTHERS of the other anchors."""
    spans = base_spans(text)
    near = [(k, a) for a, k, _ in spans]
    near += [(-1, m.start()) for m in ANCHOR.finditer(text) if not zlib.crc32(text[m.start() : m.start() + 40].encode()) % OTHERS and not any(a - 4 <= m.start() < b + 4 for a, _, b in spans)]
    for kind, at in near:
        lo, hi = max(0, at - 2 * WINDOW), at + 2 * WINDOW
        yield kind, text[lo:hi], at - lo, [{"a": a - lo, "k": k, "b": b - lo} for a, k, b in spans if a >= lo and b <= hi]


def examples(rows: list[tuple[int, str, int, list[tuple[int, int, int]]]], seed: int = 3) -> tuple[np.ndarray, np.ndarray]:
    """Windows around labelled spans, their rewritten forms, and around other anchors; tags by character."""
    rng = np.random.default_rng(seed)
    codes, tags = [], []

    def add(text: str, spans: list[tuple[int, int, int]], near: int) -> None:
        lo = max(0, near - int(rng.integers(4, WINDOW - 4)))
        c, t = np.full(WINDOW, CLASSES, np.int16), np.zeros(WINDOW, np.int64)
        part = classes(text[lo : lo + WINDOW])
        c[: len(part)] = part
        for a, k, b in spans:
            if a >= lo and a < lo + WINDOW:
                t[a - lo] = 1 + 2 * k
            t[max(0, a + 1 - lo) : max(0, min(WINDOW, b - lo))] = 2 + 2 * k
        codes.append(c)
        tags.append(t)

    for kind, part, near, spans in rows:
        add(part, spans, near)
        for a, k, b in spans:
            if k == kind and a == near:
                for _ in range(FORMS):
                    new = rewritten(k, part[a:b], rng)
                    add(part[:a] + new + part[b:], [x for x in spans if x[2] <= a] + [(a, k, a + len(new))] + [(x + len(new) - b + a, y, z + len(new) - b + a) for x, y, z in spans if x >= b], a)
    return (np.array(codes), np.array(tags)) if codes else (np.zeros((0, WINDOW), np.int16), np.zeros((0, WINDOW), np.int64))


def train(docs: DataFrame, sample_docs: int = SAMPLE_DOCS, epochs: int | None = None, windows: int = TRAIN_WINDOWS) -> Tagger | None:
    """Fit on documents with digits or at signs among those with the smallest hashes of their ids.

    Of the sample's spans each kind gives those with the smallest hashes, each as it is and in rewritten forms; other anchors give
    as many as a kind's spans. Together that is `windows` at most.
    """
    total = docs.count()
    if not total:
        return None
    u = F.pmod(F.xxhash64(F.col("doc_id").cast("string")), F.lit(1 << 20)) / float(1 << 20)
    some = docs.where((u < min(1.0, sample_docs / total)) & F.col("text").cast("string").rlike("[0-9@]"))

    def around(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = [pa.int32(), pa.string(), pa.int32(), pa.list_(pa.struct([("a", pa.int32()), ("k", pa.int32()), ("b", pa.int32())]))]
        for b in batches:
            rows = [r for t in b.column("text").to_pylist() for r in stretches_of(t)]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=["kind", "part", "near", "spans"])

    found = some.select(F.col("text").cast("string").alias("text")).mapInArrow(around, EXAMPLE)
    draw = F.xxhash64("part", "near")
    # one kind is one key here; its rows are short stretches of a bounded sample
    first = found.withColumn("r", F.row_number().over(Window.partitionBy("kind").orderBy(draw, "part", "near"))).where(F.col("r") <= windows // (len(KINDS) * (1 + FORMS) + 1))
    rows = [(r.kind, r.part, r.near, [tuple(x) for x in r.spans]) for r in first.orderBy("kind", "r").collect()]
    codes, tags = examples(rows)
    if not tags.any():
        return None
    tagger = Tagger()
    tagger.train(codes, tags, epochs or -(-STEPS * 64 // len(codes)))
    return tagger


def find(docs: DataFrame, tagger: Tagger | None) -> DataFrame:
    """doc_id, counts of base spans by kind, base_sha256, spans (base and added), n_added, n_spans (base and added)."""
    shared = docs.sparkSession.sparkContext.broadcast(tagger)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tagger = shared.value
        nothing = hashlib.sha256(b"").hexdigest()
        for b in batches:
            rows: list[tuple] = []
            for text in b.column("text").to_pylist():
                if not text or not ANCHOR.search(text):
                    rows.append((0, 0, 0, 0, nothing, "", 0, 0))
                    continue
                base = base_spans(text)
                more = tagger.spans(text, base) if tagger else []
                counts = [sum(k == i for _, k, _ in base) for i in range(4)]
                rows.append((*counts, hashlib.sha256(show(base).encode()).hexdigest(), show(sorted(base + more)), len(more), len(base) + len(more)))
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 8
            kinds = [pa.int64()] * 4 + [pa.string(), pa.string(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], names=["doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans", "n_added", "n_spans"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long, n_spans long")


def redacted(text: str | None, tagger: Tagger | None) -> str | None:
    """Text with each span replaced by its kind in angle brackets; overlapping spans are replaced together, named by the first."""
    if not text or not ANCHOR.search(text):
        return text
    base = base_spans(text)
    out, at = [], 0
    for a, k, b in sorted(base + (tagger.spans(text, base) if tagger else [])):
        if a >= at:
            out.append(text[at:a] + f"<{KINDS[k].upper()}>")
        at = max(at, b)
    return "".join(out) + text[at:]


def redact(docs: DataFrame, tagger: Tagger | None) -> DataFrame:
    """The documents with their text redacted, and n_chars, where there is one, set anew for texts that changed; all else stays."""
    shared = docs.sparkSession.sparkContext.broadcast(tagger)
    at, size = docs.columns.index("text"), docs.columns.index("n_chars") if dict(docs.dtypes).get("n_chars") == "bigint" else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cols = list(b.columns)
            old = cols[at].to_pylist()
            new = [redacted(t, shared.value) for t in old]
            cols[at] = pa.array(new, pa.string())
            if size is not None:
                cols[size] = pa.array([n if x == y else len(y) for n, x, y in zip(cols[size].to_pylist(), old, new, strict=True)], pa.int64())
            yield pa.RecordBatch.from_arrays(cols, names=b.schema.names)
        give_back()

    return docs.mapInArrow(run, docs.schema)
