"""Operator 6: personal data by patterns and by a character-level bidirectional LSTM with a CRF.

The base finds emails, IPv4 addresses, payment card and telephone numbers by fixed patterns with checks.
The tagger, trained in numpy from labelled spans, adds what the patterns miss, such as numbers
without a plus sign. Windows of WINDOW characters that overlap by half are scored; where they overlap the
scores are averaged, with most weight for the middle of a window, and one best path under the CRF's transitions
goes over all neighbouring windows together. Spans are read off this path, checked, and
dropped where they touch a base span.

Every accepted span holds a digit or an at sign. Windows that lie more than REACH characters away from all of
these are not decoded, so a span is missed if one of its ends lies that far from its nearest digit or at sign.

Cases: null or empty text has no spans; repeated rows and null ids map one to one; very long texts are
cut into windows and never cut short; an empty table trains on made-up samples alone; further columns of the
table, whatever their names, are not read.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.session import ship_package

KINDS = ("email", "ip", "card", "phone")
WINDOW, STEP = 64, 32
#: Windows farther than this from every digit and at sign are not decoded.
REACH = 64
HIDDEN, EMBED = 12, 8
#: At most so many documents with base spans are learned from, drawn by hash of their id.
TRAIN_DOCS = 400
TRAIN_WINDOWS = 3_000
#: Samples with numbers in known and unknown forms, made up from a seed.
MADE_UP = 2_000
#: At most so many windows come from one text, drawn at random from all of its cues.
CUES_OF_A_TEXT = 10
EPOCHS = 7

_EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
_CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_CUE = re.compile(r"[0-9@]")
_DIGITS = re.compile(r"[0-9]+")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = 2 * d - 9 if d > 4 else 2 * d
        total += d
    return total % 10 == 0


def _digits(s: str) -> str:
    return "".join(_DIGITS.findall(s))


def _emails(text: str) -> Iterator[re.Match]:
    """Matches of the email pattern; starts the search near each at sign, which every match has."""
    at, done = text.find("@"), 0
    while at >= 0:
        start = at
        while start > done and (text[start - 1].isascii() and (text[start - 1].isalnum() or text[start - 1] in "._%+-")):
            start -= 1
        m = _EMAIL.match(text, start) if start < at else None
        if m:
            yield m
            done = m.end()
            at = text.find("@", done)
        else:
            at = text.find("@", at + 1)


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, end, kind) of the base patterns, by start, then kind."""
    found = [(m.start(), m.end(), 0) for m in _emails(text)] if "@" in text else []
    if _CUE.search(text):
        for m in _IP.finditer(text):
            if all(len(p.lstrip("0")) <= 3 and int(p) <= 255 for p in m.group().split(".")):
                found.append((m.start(), m.end(), 1))
        for m in _CARD.finditer(text):
            digits = _digits(m.group())
            if 14 <= len(digits) <= 19 and luhn(digits):
                found.append((m.start(), m.end(), 2))
        for m in _PHONE.finditer(text) if "+" in text else ():
            if 10 <= len(_digits(m.group())) <= 15:
                found.append((m.start(), m.end(), 3))
    return in_order(found)


def in_order(spans: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """By start, then kind; spans that are alike in both keep the order of their ends."""
    return sorted(spans, key=lambda x: (x[0], x[2], x[1]))


def digest(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, e, k in in_order(spans))


# --- the tagger -----------------------------------------------------------------------------------

#: Character classes: 0 padding, then ASCII printable characters, then letters beyond ASCII, white space, the rest.
N_CLASSES = 1 + 95 + 3
TAGS = 1 + 2 * len(KINDS)  # outside, then begin and inside of each kind


def char_classes(text: str) -> np.ndarray:
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    out = np.full(len(codes), 96, np.int64)
    plain = (codes >= 32) & (codes < 127)
    out[plain] = codes[plain] - 31
    out[(codes >= 9) & (codes <= 13)] = 97
    out[(codes >= 48) & (codes <= 57)] = 17  # one class for all digits
    return out


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


class Tagger:
    """Embedding, one LSTM each way, a linear layer and CRF transitions, all in numpy."""

    def __init__(self, seed: int = 7):
        r = np.random.default_rng(seed)
        scale = lambda *s: (r.standard_normal(s) / np.sqrt(s[0])).astype(np.float32)
        self.p = {"E": scale(N_CLASSES, EMBED) * 3, "O": scale(2 * HIDDEN, TAGS), "ob": np.zeros(TAGS, np.float32), "T": np.zeros((TAGS, TAGS), np.float32)}
        for way in "fb":
            self.p[way + "W"] = scale(EMBED + HIDDEN, 4 * HIDDEN)
            self.p[way + "c"] = np.zeros(4 * HIDDEN, np.float32)
            self.p[way + "c"][HIDDEN : 2 * HIDDEN] = 1

    def _lstm(self, x: np.ndarray, way: str, keep: list | None) -> np.ndarray:
        n, steps, _ = x.shape
        h, c = np.zeros((n, HIDDEN), np.float32), np.zeros((n, HIDDEN), np.float32)
        out = np.empty((n, steps, HIDDEN), np.float32)
        for t in range(steps) if way == "f" else range(steps - 1, -1, -1):
            z = np.concatenate((x[:, t], h), 1)
            g = z @ self.p[way + "W"] + self.p[way + "c"]
            i, f, o = _sigmoid(g[:, :HIDDEN]), _sigmoid(g[:, HIDDEN : 2 * HIDDEN]), _sigmoid(g[:, 2 * HIDDEN : 3 * HIDDEN])
            a, before = np.tanh(g[:, 3 * HIDDEN :]), c
            c = f * before + i * a
            tc = np.tanh(c)
            h = o * tc
            out[:, t] = h
            if keep is not None:
                keep.append((t, z, i, f, o, a, before, tc))
        return out

    def scores(self, classes: np.ndarray, keep: dict | None = None) -> np.ndarray:
        """Emission scores, windows x positions x tags."""
        x = self.p["E"][classes]
        kept = {"f": [], "b": []} if keep is not None else {"f": None, "b": None}
        h = np.concatenate((self._lstm(x, "f", kept["f"]), self._lstm(x, "b", kept["b"])), 2)
        if keep is not None:
            keep.update(h=h, classes=classes, **kept)
        return h @ self.p["O"] + self.p["ob"]

    def best_path(self, e: np.ndarray, sizes: np.ndarray) -> np.ndarray:
        """Viterbi decoding of a batch of scores, each as far as its size; tags behind it mean nothing."""
        n, steps, _ = e.shape
        back = np.empty((n, steps, TAGS), np.int8)
        v, rows, last = e[:, 0], np.arange(n), np.empty(n, np.int64)
        for t in range(steps):
            if t:
                m = v[:, :, None] + self.p["T"]
                back[:, t] = m.argmax(1)
                v = m.max(1) + e[:, t]
            ends = sizes - 1 == t
            last[ends] = v[ends].argmax(1)
        path = np.zeros((n, steps), np.int64)
        path[rows, sizes - 1] = last
        for t in range(steps - 1, 0, -1):
            inside = t < sizes
            path[inside, t - 1] = back[rows[inside], t, path[inside, t]]
        return path

    def step(self, classes: np.ndarray, tags: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        """Negative log likelihood and gradients of a batch."""
        keep: dict = {}
        e = self.scores(classes, keep).astype(np.float64)
        n, steps, _ = e.shape
        trans = self.p["T"].astype(np.float64)
        log_sum = lambda a, axis: (m := a.max(axis, keepdims=True)).squeeze(axis) + np.log(np.exp(a - m).sum(axis))
        alpha, beta = np.empty_like(e), np.zeros_like(e)
        alpha[:, 0] = e[:, 0]
        for t in range(1, steps):
            alpha[:, t] = log_sum(alpha[:, t - 1][:, :, None] + trans, 1) + e[:, t]
        for t in range(steps - 2, -1, -1):
            beta[:, t] = log_sum(trans[None] + (e[:, t + 1] + beta[:, t + 1])[:, None, :], 2)
        z = log_sum(alpha[:, -1], 1)
        own, pairs = np.take_along_axis(e, tags[:, :, None], 2), (tags[:, :-1], tags[:, 1:])
        gold = own.sum((1, 2)) + trans[pairs].sum(1)
        d_e = np.exp(alpha + beta - z[:, None, None])
        d_t = np.exp(alpha[:, :-1, :, None] + trans + (e + beta)[:, 1:, None, :] - z[:, None, None, None]).sum((0, 1))
        np.add.at(d_t, pairs, -1)
        np.put_along_axis(d_e, tags[:, :, None], np.take_along_axis(d_e, tags[:, :, None], 2) - 1, 2)
        d_e = (d_e / n).astype(np.float32)
        g = {k: np.zeros_like(v) for k, v in self.p.items()}
        g["T"] = (d_t / n).astype(np.float32)
        flat = d_e.reshape(-1, TAGS)
        g["O"], g["ob"] = keep["h"].reshape(-1, 2 * HIDDEN).T @ flat, flat.sum(0)
        d_h = d_e @ self.p["O"].T
        d_x = np.zeros((n, steps, EMBED), np.float32)
        for way, part in (("f", d_h[:, :, :HIDDEN]), ("b", d_h[:, :, HIDDEN:])):
            dh, dc = np.zeros((n, HIDDEN), np.float32), np.zeros((n, HIDDEN), np.float32)
            for t, zt, i, f, o, a, before, tc in reversed(keep[way]):
                dh = dh + part[:, t]
                dc = dc + dh * o * (1 - tc * tc)
                dg = np.concatenate((dc * a * i * (1 - i), dc * before * f * (1 - f), dh * tc * o * (1 - o), dc * i * (1 - a * a)), 1)
                g[way + "W"] += zt.T @ dg
                g[way + "c"] += dg.sum(0)
                dz = dg @ self.p[way + "W"].T
                d_x[:, t] += dz[:, :EMBED]
                dh, dc = dz[:, EMBED:], dc * f
        np.add.at(g["E"], keep["classes"].ravel(), d_x.reshape(-1, EMBED))
        return float((z - gold).mean()), g

    def fit(self, classes: np.ndarray, tags: np.ndarray, epochs: int = EPOCHS, batch: int = 64, rate: float = 0.02, seed: int = 11) -> list[float]:
        """Adam over shuffled batches; gives the loss of each epoch."""
        r, losses, k = np.random.default_rng(seed), [], 0
        m, v = ({n: np.zeros_like(x) for n, x in self.p.items()} for _ in range(2))
        for _ in range(epochs):
            total = []
            order = r.permutation(len(classes))
            for at in range(0, len(order), batch):
                pick = order[at : at + batch]
                loss, g = self.step(classes[pick], tags[pick])
                total.append(loss)
                k += 1
                for n in self.p:
                    grad = np.clip(g[n], -5, 5)
                    m[n] = 0.9 * m[n] + 0.1 * grad
                    v[n] = 0.99 * v[n] + 0.01 * grad * grad
                    self.p[n] = (self.p[n] - rate * (m[n] / (1 - 0.9**k)) / (np.sqrt(v[n] / (1 - 0.99**k)) + 1e-6)).astype(np.float32)
            losses.append(float(np.mean(total)))
        return losses


def tags_of(length: int, spans: list[tuple[int, int, int]]) -> np.ndarray:
    tags = np.zeros(length, np.int64)
    for s, e, k in spans:
        tags[s] = 1 + 2 * k
        tags[s + 1 : e] = 2 + 2 * k
    return tags


def spans_of(tags: np.ndarray) -> list[tuple[int, int, int]]:
    """Runs of begin and inside tags of one kind."""
    found, at = [], 0
    for i in np.flatnonzero(tags).tolist():
        if i < at:
            continue
        kind, at = (tags[i] - 1) // 2, i + 1
        while at < len(tags) and tags[at] == 2 + 2 * kind:
            at += 1
        found.append((i, at, int(kind)))
    return found


def window_starts(length: int) -> list[int]:
    return list(range(0, max(1, length - WINDOW + STEP), STEP))


def _padded(classes: np.ndarray, start: int) -> np.ndarray:
    part = classes[start : start + WINDOW]
    return part if len(part) == WINDOW else np.concatenate((part, np.zeros(WINDOW - len(part), np.int64)))


def varied(text: str, spans: list[tuple[int, int, int]], r: np.random.Generator) -> tuple[str, list[tuple[int, int, int]]]:
    """Rewrites labelled spans into forms that the patterns miss: numbers without plus or with other separators."""
    out, done, moved = [], 0, []
    length = 0
    for s, e, k in spans:
        if s < done:
            continue
        lead, piece = text[done:s], text[s:e]
        if k == 3 and r.random() < 0.7:
            digits = _digits(piece)[-10:]
            shapes = [f"({digits[:3]}) {digits[3:6]}-{digits[6:]}", f"{digits[:3]}-{digits[3:6]}-{digits[6:]}", f"{digits[:3]}.{digits[3:6]}.{digits[6:]}", f"{digits[:3]} {digits[3:6]} {digits[6:]}"]
            piece = shapes[int(r.integers(len(shapes)))]
        elif k == 2 and r.random() < 0.5:
            digits, sep = _digits(piece), ". -/"[int(r.integers(4))]
            piece = sep.join(digits[i : i + 4] for i in range(0, len(digits), 4))
        out += [lead, piece]
        length += len(lead)
        moved.append((length, length + len(piece), k))
        length += len(piece)
        done = e
    return "".join([*out, text[done:]]), moved


def made_up(n: int, r: np.random.Generator) -> list[tuple[str, list[tuple[int, int, int]]]]:
    """Labelled samples with numbers that are personal data and numbers that aren't."""
    word = lambda: "".join(chr(97 + int(c)) for c in r.integers(0, 26, int(r.integers(2, 9))))
    digit = lambda k: "".join(str(int(c)) for c in r.integers(0, 10, k))
    out = []
    for _ in range(n):
        before, after = " ".join(word() for _ in range(int(r.integers(0, 9)))), " ".join(word() for _ in range(int(r.integers(0, 9))))
        c = int(r.integers(8))
        kind, body = -1, ""
        if c == 0:
            kind, body = 0, f"{word()}.{digit(2)}@{word()}.{word()}"
        elif c == 1:
            kind, body = 1, ".".join(str(int(x)) for x in r.integers(0, 256, 4))
        elif c == 2:
            digits = digit(15)
            kind, body = 2, next(digits + str(d) for d in range(10) if luhn(digits + str(d)))
        elif c in (3, 4):
            kind, body = 3, f"+{digit(int(r.integers(1, 3)))} ({digit(3)}) {digit(3)}-{digit(4)}"
        elif c == 5:
            body = f"{word()} = \"{hashlib.sha256(str(r.integers(1 << 30)).encode()).hexdigest()[: int(r.integers(16, 50))]}\""
        elif c == 6:
            body = f"{digit(4)}-{digit(2)}-{digit(2)}" if r.random() < 0.5 else digit(int(r.integers(1, 9)))
        else:
            body = f"v{digit(1)}.{digit(2)}.{digit(1)}" if r.random() < 0.5 else f"{digit(3)},{digit(3)}.{digit(2)}"
        if kind >= 2 and r.random() < 0.6:
            body, _ = varied(body, [(0, len(body), kind)], r)
        text = f"{before} {body}"
        start = len(before) + 1
        spans = [(start, start + len(body), kind)] if kind >= 0 else []
        text = f"{text}{['', '.', ',', ' '][int(r.integers(4))]} {after}"
        out.append((text, spans))
    return out


def train_tagger(docs: DataFrame) -> Tagger:
    """Trains on the base spans of at most TRAIN_DOCS documents and on made-up samples."""
    cue = F.col("text").rlike(r"[0-9]@|@[a-z]|[0-9][ .()-]?[0-9]{3}|\+[0-9]")
    ids = [r.doc_id for r in docs.where(cue & F.col("doc_id").isNotNull()).select("doc_id").orderBy(F.xxhash64("doc_id"), "doc_id").limit(TRAIN_DOCS).collect()]
    rows = docs.where(F.col("doc_id").isin(ids)).orderBy("doc_id", "text").limit(TRAIN_DOCS).select("text").collect() if ids else []
    r = np.random.default_rng(3)
    samples = made_up(MADE_UP, r)
    for row in rows:
        text = row.text or ""
        spans, last = [], 0
        for s in base_spans(text):
            if s[0] >= last:
                spans.append(s)
                last = s[1]
        samples += [(text, spans), varied(text, spans, r)]
    windows, tags = [], []
    for text, spans in samples:
        classes, all_tags = char_classes(text), tags_of(len(text), spans)
        cues = np.array([m.start() for m in _CUE.finditer(text)], np.int64)
        # From all cues of a text, wherever they stand.
        for at in r.permutation(cues)[:CUES_OF_A_TEXT].tolist():
            start = max(0, at - int(r.integers(WINDOW)))
            windows.append(_padded(classes, start))
            tags.append(_padded(all_tags, start))
    pick = r.permutation(len(windows))[:TRAIN_WINDOWS]
    tagger = Tagger()
    tagger.fit(np.array(windows)[pick], np.array(tags)[pick])
    return tagger


def accepted(text: str, start: int, end: int, kind: int) -> bool:
    """The check that a span of the tagger must pass."""
    piece = text[start:end]
    digits = _digits(piece)
    edge = (start == 0 or not text[start - 1].isalnum()) and (end == len(text) or not text[end : end + 1].isalnum())
    if not edge or piece != piece.strip():
        return False
    if kind == 0:
        return bool(re.fullmatch(r"[^\s@]+@[^\s@]+\.[^\s@.]+", piece))
    if kind == 1:
        return bool(re.fullmatch(r"[0-9]{1,3}(\.[0-9]{1,3}){3}", piece)) and all(int(x) <= 255 for x in piece.split("."))
    if kind == 2:
        return 14 <= len(digits) <= 19 and luhn(digits) and bool(re.fullmatch(r"[0-9][0-9 ./-]+[0-9]", piece))
    return 10 <= len(digits) <= 15 and bool(re.fullmatch(r"\+?[(0-9][0-9 ().-]+[0-9]", piece)) and not (len(digits) >= 14 and luhn(digits))


def _regions(starts: list[int], near: np.ndarray) -> list[list[int]]:
    """Runs of neighbouring windows that are decoded."""
    out: list[list[int]] = []
    for s in (s for s, n in zip(starts, near.tolist(), strict=True) if n):
        if out and s == out[-1][-1] + STEP:
            out[-1].append(s)
        else:
            out.append([s])
    return out


#: Weight of a window's scores at each of its places: most in the middle, where both directions have seen most.
_TAPER = np.minimum(np.arange(1, WINDOW + 1), np.arange(WINDOW, 0, -1)).astype(np.float32)[:, None]


def tagged_spans(texts: list[str], tagger: Tagger, batch: int = 512) -> list[list[tuple[int, int, int]]]:
    """Spans of the tagger in each text: the scores of overlapping windows are averaged, and one best path goes over all of a region."""
    regions, classes = [], []
    for k, text in enumerate(texts):
        cues = np.array([m.start() for m in _CUE.finditer(text)], np.int64)
        classes.append(char_classes(text) if len(cues) else np.zeros(0, np.int64))
        if len(cues):
            starts = window_starts(len(text))
            near = np.searchsorted(cues, np.array(starts) + WINDOW + REACH) - np.searchsorted(cues, np.array(starts) - REACH)
            regions += [(k, r) for r in _regions(starts, near)]
    found: list[list[tuple[int, int, int]]] = [[] for _ in texts]
    regions.sort(key=lambda x: len(x[1]))
    at = 0
    while at < len(regions):
        # Regions of about the same length share a batch: at most batch windows, or one region.
        part, most = [], 0
        while at < len(regions) and (not part or max(most, len(regions[at][1])) * (len(part) + 1) <= batch):
            most = max(most, len(regions[at][1]))
            part.append(regions[at])
            at += 1
        found_in = _best_tags(tagger, part, classes, batch)
        for (k, starts), tags in zip(part, found_in, strict=True):
            found[k] += [(s + starts[0], e + starts[0], kind) for s, e, kind in spans_of(tags)]
    return [[x for x in in_order(f) if accepted(text, *x)] for f, text in zip(found, texts, strict=True)]


def _best_tags(tagger: Tagger, regions: list[tuple[int, list[int]]], classes: list[np.ndarray], batch: int) -> list[np.ndarray]:
    """Tags of each region's characters, by one best path over the averaged scores of its windows."""
    sizes = [min(len(classes[k]), starts[-1] + WINDOW) - starts[0] for k, starts in regions]
    total = np.zeros((len(regions), max(len(s) for _, s in regions) * STEP + WINDOW, TAGS), np.float32)
    weight = np.zeros((*total.shape[:2], 1), np.float32)
    todo = [(i, k, s, s - starts[0]) for i, (k, starts) in enumerate(regions) for s in starts]
    for at in range(0, len(todo), batch):
        part = todo[at : at + batch]
        scores = tagger.scores(np.array([_padded(classes[k], s) for _, k, s, _ in part]))
        for (i, _, _, lo), e in zip(part, scores, strict=True):
            total[i, lo : lo + WINDOW] += e * _TAPER
            weight[i, lo : lo + WINDOW] += _TAPER
    path = tagger.best_path(total / np.maximum(weight, 1), np.array(sizes))
    return [path[i, :n] for i, n in enumerate(sizes)]


def find_private(docs: DataFrame, tagger: Tagger | None = None) -> DataFrame:
    """One row (doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_added): counts are of base spans, n_added of those that the tagger adds."""
    ship_package(docs.sparkSession)
    tagger = tagger or train_tagger(docs.select("doc_id", "text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part = b.slice(at, 512)
                texts = [t or "" for t in part.column(1).to_pylist()]
                base = [base_spans(t) for t in texts]
                found = tagged_spans(texts, tagger)
                spans, added = [], []
                for own, more in zip(base, found, strict=True):
                    extra = [x for x in more if not any(x[0] < e and s < x[1] for s, e, _ in own)]
                    spans.append(digest(own + extra))
                    added.append(len(extra))
                counts = [pa.array([sum(x[2] == k for x in own) for own in base], pa.int64()) for k in range(len(KINDS))]
                sha = [hashlib.sha256(digest(own).encode()).hexdigest() for own in base]
                yield pa.RecordBatch.from_arrays([part.column(0), *counts, pa.array(sha, pa.string()), pa.array(spans, pa.string()), pa.array(added, pa.int64())], ["doc_id", *(f"n_{k}" for k in KINDS), "base_sha256", "spans", "n_added"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, n_email bigint, n_ip bigint, n_card bigint, n_phone bigint, base_sha256 string, spans string, n_added bigint")
