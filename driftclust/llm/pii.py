"""Personal data: exact patterns, and a linear-chain CRF that adds to them.

The patterns are the base and always stay. The CRF labels the words of a text
in order: its features are the word itself and its shape (character classes with
repeats collapsed) at the place, before and after it. It is trained at each use
from a small labelled table, made by rule, and adds spans of kinds email, ip,
card, phone and secret that overlap no base span. Decoding is Viterbi, in NumPy
batches of segments of up to 64 words; segments in which no label can beat
"outside" whatever the transitions are decided without it, by a bound that is
exact.

Null text is empty. Places are code points, ends exclusive. Rows with a
repeated id are searched each; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import random
import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import kernels
from .scratch import prepare

KINDS = ("email", "ip", "card", "phone")
LABELS = ("", "email", "ip", "card", "phone", "secret")
SEGMENT = 64
BITS = 18

_DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
# The look-behind changes no match: a start inside a run of digits fails or
# succeeds with the run's first digit. It keeps long runs from costing squares.
_IP = re.compile(r"(?<![0-9])[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGIT = re.compile("[0-9]")


def _luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if k % 2:
            d = d * 2 - 9 * (d > 4)
        total += d
    return total % 10 == 0


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind index, end) of all base matches, in order."""
    out = []
    p, done = text.find("@"), 0
    while p >= 0:
        s = p
        while s > done and text[s - 1] in _LOCAL:
            s -= 1
        if s < p and (m := _DOMAIN.match(text, p + 1)):
            done = m.end()
            out.append((s, 0, done))
        p = text.find("@", max(p + 1, done))
    if first := _DIGIT.search(text):
        at = first.start()
        for m in _IP.finditer(text, at):
            if all(len(x.lstrip("0")) <= 3 and int(x.lstrip("0") or 0) <= 255 for x in m[0].split(".")):
                out.append((m.start(), 1, m.end()))
        for m in _CARD.finditer(text, at):
            if m.end() - m.start() >= 12:
                digits = m[0].replace(" ", "").replace("-", "")
                if 12 <= len(digits) <= 19 and _luhn(digits):
                    out.append((m.start(), 2, m.end()))
        if "+" in text:
            for m in _PHONE.finditer(text):
                if 9 <= sum(c.isdigit() for c in m[0]) <= 15:
                    out.append((m.start(), 3, m.end()))
    return sorted(out)


def labelled_table(rows: int = 900, seed: int = 5) -> list[tuple[list[str], list[int]]]:
    """Labelled word sequences by rule: forms of each kind, and look-alikes."""
    rng = random.Random(seed)
    syllables = "an er on re he in ed nd ha at en es or nt ea ti to it st io le is ou ar as de rt ve der und ein le la que os ía é ä ß".split()

    def word():
        w = "".join(rng.choice(syllables) for _ in range(rng.randint(1, 5)))
        w = rng.choice([w, w, w, w.capitalize(), w.upper()])
        return w + rng.choice(["", "", "", "", "", ",", ".", "!!", "?", ":", "...", "%%%", "***", "$$$", ".&&&", ",###", ".!!", ";", '"', ")"])

    def digits(n):
        return "".join(rng.choice("0123456789") for _ in range(n))

    def hexes(n):
        return "".join(rng.choice("0123456789abcdef") for _ in range(n))

    def name():
        return "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randint(2, 8)))

    def card():
        body = digits(15)
        for c in "0123456789":
            if _luhn(body + c):
                return body + c
        raise AssertionError

    def entity():
        kind = rng.randint(1, 5)
        if kind == 1:
            host = f"{name()}{rng.choice(['', rng.randint(0, 9)])}.{rng.choice(['example', name()])}.{rng.choice(['com', 'org', 'net', 'de'])}"
            form = rng.choice([f"{name()}.{digits(2)}@{host}", f"{name()}_{name()}@{host}", f"{name()}[at]{host}", f"{name()}(at){host}", f"<{name()}@{host}>"])
            return [(form, 1)]
        if kind == 2:
            return [(".".join(str(rng.randint(1, 255)) for _ in range(4)) + rng.choice(["", ",", ".", ":" + digits(4)]), 2)]
        if kind == 3:
            c = card()
            form = rng.choice([c, " ".join(c[k : k + 4] for k in range(0, 16, 4)), "-".join(c[k : k + 4] for k in range(0, 16, 4))])
            return [(w, 3) for w in form.split()]
        if kind == 4:
            form = rng.choice([f"+1 ({digits(3)}) {digits(3)}-{digits(4)}", f"({digits(3)}) {digits(3)}-{digits(4)}", f"{digits(3)}-{digits(3)}-{digits(4)}", f"+{rng.randint(10, 99)} {digits(3)} {digits(7)}", f"{digits(3)}.{digits(3)}.{digits(4)}"])
            return [(w, 4) for w in form.split()]
        key = rng.choice(["password", "passwd", "token", "secret", "api_key", "apikey", "key"])
        value = rng.choice([hexes(rng.choice([16, 18, 32, 40])), name() + digits(6) + name()])
        form = rng.choice([[(f"{key}={value}", 5)], [(key, 0), ("=", 0), (f'"{value}"', 5)], [(f"{key}:", 0), (value, 5)], [(f'{key}="{value}"', 5)]])
        return form

    def negative():
        return [(rng.choice([digits(rng.randint(1, 4)), f"{digits(4)}-{digits(2)}-{digits(2)}", f"v{rng.randint(1, 9)}.{rng.randint(0, 20)}.{rng.randint(0, 9)}", f"{digits(2)}:{digits(2)}", f"#{digits(5)}", f"{digits(3)},{digits(3)}", f"{digits(2)}.{digits(2)}", "=", "|", "at", f"(c) {digits(4)}".split()[1], f"{name()}-{name()}", f"{name()}/{name()}", "|", "-", "*", "@", "##", "---", "http://" + name(), f"{name()}.{name()}", "key", "token", "password"]), 0)]

    out = []
    for _ in range(rows):
        seq: list[tuple[str, int]] = []
        for _ in range(rng.randint(0, 3)):
            seq += [(word(), 0) for _ in range(rng.randint(2, 8))]
            seq += entity() if rng.random() < 0.6 else negative()
        seq += [(word(), 0) for _ in range(rng.randint(2, 10))]
        seq = [(w, y) for w, y in seq if w]
        out.append(([w for w, _ in seq], [y for _, y in seq]))
    return out


_CLASS = np.arange(256, dtype=np.uint8)
_CLASS[65:91] = 65
_CLASS[97:123] = 97
_CLASS[48:58] = 57
_CLASS[128:] = 128
#: A bit for each character class, for the set of classes in a word.
_BIT = np.full(256, 1 << 15, np.uint32)
for _bit, _chars in enumerate((b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"ghijklmnopqrstuvwxyz", b"abcdef", b"0123456789", b"@", b".", b"-", b"_", b"=", b"\"'", b"(", b")", b"+", b":", bytes(range(128, 256)))):
    _BIT[list(_chars)] = 1 << _bit
_BIT[[32, *range(9, 14)]] = 0


def word_features(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """(words, 5): slots of the word, its shape and the set of its character
    classes, the latter two also with its length."""
    n = len(data)
    kind = _CLASS[data]
    new = np.ones(n, bool)
    new[1:] = kind[1:] != kind[:-1]
    new[starts] = True
    runs = np.flatnonzero(new)
    # Shapes are hashed over the first bytes of runs, laid side by side.
    first, last = np.searchsorted(runs, starts), np.searchsorted(runs, ends)
    shape = kernels.span_hashes(kind[runs], first, last, fold=False)
    length = (np.minimum(np.floor(np.log2(ends - starts) * 2), 12).astype(np.uint64) + np.uint64(2)) * np.uint64(0x9E3779B97F4A7C15)
    classes = np.bitwise_or.reduceat(_BIT[data], starts).astype(np.uint64)
    exact = kernels.span_hashes(data, starts, ends)
    out = np.stack([exact, kernels.mix(shape + np.uint64(1)), kernels.mix(shape + length), kernels.mix(classes + np.uint64(1 << 40)), kernels.mix(classes + length + np.uint64(1 << 41))], axis=1)
    return (out >> np.uint64(64 - BITS)).astype(np.int32)


@dataclass(frozen=True)
class Crf:
    """emit: (3 places, slots, labels); bias: of labels; step: from, to."""

    slots: np.ndarray
    emit: np.ndarray
    bias: np.ndarray
    step: np.ndarray

    def tables(self) -> np.ndarray:
        t = np.zeros((3, 1 << BITS, len(LABELS)), np.float32)
        t[:, self.slots] = self.emit
        return t


def _laid_out(f: np.ndarray, row: np.ndarray, fill: int) -> np.ndarray:
    """Features of the word before, the word, the word after: (words, 3, k)."""
    n = len(f)
    out = np.full((n, 3, f.shape[1]), fill, f.dtype)
    out[:, 1] = f
    if n > 1:
        same = (row[1:] == row[:-1])[:, None]
        out[1:, 0] = np.where(same, f[:-1], fill)
        out[:-1, 2] = np.where(same, f[1:], fill)
    return out


def train(table: list[tuple[list[str], list[int]]], rounds: int = 100, rate: float = 0.3, l2: float = 2e-3) -> Crf:
    """Maximum likelihood by full gradients, forward-backward over all rows at once."""
    texts = [" ".join(w).encode() for w, _ in table]
    data, offsets = kernels.utf8(pa.array([t.decode() for t in texts]))
    starts, ends = kernels.words(data, offsets)
    row = np.searchsorted(offsets, starts, side="right") - 1
    y = np.concatenate([np.array(v) for _, v in table])
    raw = _laid_out(word_features(data, starts, ends), row, -1)
    slots, at = np.unique(np.concatenate([[-1], raw.reshape(-1)]), return_inverse=True)
    at = at[1:].reshape(raw.shape)
    k, s = len(LABELS), len(slots)
    count = np.bincount(row, minlength=len(table))
    longest, place = int(count.max()), np.arange(len(row)) - np.repeat(np.cumsum(count) - count, count)
    live = np.zeros((len(table), longest), bool)
    live[row, place] = True
    gold = np.eye(k)[y]
    emit, step, bias = np.zeros((3, s, k)), np.zeros((k, k)), np.zeros(k)
    seen_e, seen_s, seen_b = np.full_like(emit, 1e-8), np.full_like(step, 1e-8), np.full(k, 1e-8)
    width = at.shape[2]
    pairs = np.flatnonzero(row[1:] == row[:-1])
    gold_step = np.zeros((k, k))
    np.add.at(gold_step, (y[pairs], y[pairs + 1]), 1)
    for _ in range(rounds):
        score = bias + sum(emit[p, at[:, p, j]] for p in range(3) for j in range(width))
        em = np.zeros((len(table), longest, k))
        em[row, place] = score
        e, t = np.exp(em - em.max(axis=2, keepdims=True)), np.exp(step)
        fwd, bwd = np.zeros_like(e), np.ones_like(e)
        fwd[:, 0] = e[:, 0] / e[:, 0].sum(axis=1, keepdims=True)
        for i in range(1, longest):
            a = (fwd[:, i - 1] @ t) * e[:, i]
            fwd[:, i] = np.where(live[:, i, None], a / np.maximum(a.sum(axis=1, keepdims=True), 1e-300), 0)
        expected = np.zeros((k, k))
        for i in range(longest - 2, -1, -1):
            nxt = e[:, i + 1] * bwd[:, i + 1]
            b = nxt @ t.T
            bwd[:, i] = np.where(live[:, i + 1, None], b / b.sum(axis=1, keepdims=True), 1)
            both = fwd[:, i, :, None] * t * nxt[:, None, :]
            z = both.sum(axis=(1, 2))
            on = live[:, i + 1] & (z > 0)
            expected += (both[on] / z[on, None, None]).sum(axis=0)
        m = fwd * bwd
        m = (m / np.maximum(m.sum(axis=2, keepdims=True), 1e-300))[row, place]
        g = np.stack([sum(np.stack([np.bincount(at[:, p, j], weights=(m - gold)[:, c], minlength=s) for c in range(k)], axis=1) for j in range(width)) for p in range(3)]) / len(table) + l2 * emit
        gs = (expected - gold_step) / len(table) + l2 * step
        gb = (m - gold).sum(axis=0) / len(table)
        seen_b += gb * gb
        bias -= rate * gb / np.sqrt(seen_b)
        seen_e += g * g
        seen_s += gs * gs
        emit -= rate * g / np.sqrt(seen_e)
        step -= rate * gs / np.sqrt(seen_s)
    known = slots >= 0
    return Crf(slots[known], emit[:, known].astype(np.float32), bias.astype(np.float32), step.astype(np.float32))


def viterbi(em: np.ndarray, live: np.ndarray, step: np.ndarray) -> np.ndarray:
    """Best labels of (segments, places); places that aren't live get 0."""
    n, longest, k = em.shape
    back = np.zeros((n, longest, k), np.int8)
    best = em[:, 0].copy()
    for i in range(1, longest):
        way = best[:, :, None] + step
        back[:, i] = way.argmax(axis=1)
        nxt = way.max(axis=1) + em[:, i]
        best = np.where(live[:, i, None], nxt, best)
    out = np.zeros((n, longest), np.int8)
    label = best.argmax(axis=1)
    for i in range(longest - 1, -1, -1):
        out[:, i] = np.where(live[:, i], label, 0)
        if i:
            label = np.where(live[:, i], back[np.arange(n), i, label], label)
    return out


def decode(data: np.ndarray, offsets: np.ndarray, tables: np.ndarray, bias: np.ndarray, step: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(row, start byte, end byte, label) of labelled runs of words.

    Segments end with a row, at a line end, or after SEGMENT words.
    """
    starts, ends = kernels.words(data, offsets)
    none = np.zeros(0, np.int64)
    if not len(starts):
        return none, none, none, none
    row = np.searchsorted(offsets, starts, side="right") - 1
    f = word_features(data, starts, ends)
    em = np.tile(bias, (len(starts), 1))
    used = tables.any(axis=2)
    same = row[1:] == row[:-1]
    for p in range(3):
        for j in range(f.shape[1]):
            at = np.flatnonzero(used[p, f[:, j]])
            gain = tables[p, f[at, j]]
            to = at + 1 - p
            if p != 1:
                ok = (to >= 0) & (to < len(row))
                ok[ok] &= row[to[ok]] == row[at[ok]]
                at, to, gain = at[ok], to[ok], gain[ok]
            em[to] += gain
    lines = np.concatenate([[0], np.cumsum(data == 10)])[starts]
    fresh = np.ones(len(starts), bool)
    fresh[1:] = ~same | (lines[1:] != lines[:-1])
    lead = np.flatnonzero(fresh)
    size = np.diff(np.append(lead, len(starts)))
    inside = np.arange(len(starts)) - np.repeat(lead, size)
    fresh |= inside % SEGMENT == 0
    lead = np.flatnonzero(fresh)
    size = np.diff(np.append(lead, len(starts)))
    # Leaving "outside" gains at most the best step over staying, twice a word.
    gain = 2 * max(0.0, float(step.max() - step[0, 0]))
    open_ = em[:, 1:].max(axis=1) + gain > em[:, 0]
    some = np.flatnonzero(np.logical_or.reduceat(open_, lead))
    label = np.zeros(len(starts), np.int8)
    for lo in range(0, len(some), 4096):
        seg = some[lo : lo + 4096]
        w = kernels.segments(lead[seg], size[seg])
        r = np.repeat(np.arange(len(seg)), size[seg])
        c = np.arange(len(w)) - np.repeat(np.cumsum(size[seg]) - size[seg], size[seg])
        grid, live = np.zeros((len(seg), int(size[seg].max()), em.shape[1]), np.float32), np.zeros((len(seg), int(size[seg].max())), bool)
        grid[r, c], live[r, c] = em[w], True
        label[w] = viterbi(grid, live, step)[r, c]
    on = np.flatnonzero(label)
    if not len(on):
        return none, none, none, none
    new = np.ones(len(on), bool)
    new[1:] = (on[1:] != on[:-1] + 1) | (label[on[1:]] != label[on[:-1]]) | fresh[on[1:]] | (label[on[1:]] == 5)
    a = np.flatnonzero(new)
    b = np.append(a[1:], len(on)) - 1
    return row[on[a]], starts[on[a]], ends[on[b]], label[on[a]].astype(np.int64)


_VALUE = re.compile(r"""^(?:[A-Za-z_]+\s*[=:]\s*)?["'<(]*(.*?)["'>).,;!?|]*$""", re.S)


def added_spans(text: str, start: int, end: int, label: int) -> tuple[int, int]:
    """The span without quotes and punctuation around it, or a key before it."""
    m = _VALUE.match(text[start:end]) if label == 5 else re.match(r"""^["'<]*(.*?)["'>.,;!?|:]*$""", text[start:end], re.S)
    return (start + m.start(1), start + m.end(1)) if m else (start, end)


def find(docs: DataFrame, model: Crf | None = None) -> DataFrame:
    """doc_id, counts of base spans by kind, base_sha256, spans (base and added),
    n_spans (how many these are), of every row."""
    spark = docs.sparkSession
    prepare(spark)
    shared = spark.sparkContext.broadcast(model or train(labelled_table()))

    def search(batches):
        tables, bias, step = shared.value.tables(), shared.value.bias, shared.value.step
        for batch in batches:
            column = batch.column("text")
            data, offsets = kernels.utf8(column)
            texts = column.to_pylist()
            more: dict[int, list[tuple[int, int, int]]] = {}
            for lo, hi in kernels.blocks(offsets):
                for row, s, e, label in zip(*(x.tolist() for x in decode(data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo], tables, bias, step)), strict=True):
                    more.setdefault(lo + row, []).append((s + int(offsets[lo]), e + int(offsets[lo]), label))
            counts, base_sha, spans, n_spans = [], [], [], []
            for r, text in enumerate(texts):
                base = base_spans(text or "")
                names = [f"{KINDS[k]}:{s}:{e}" for s, k, e in base]
                counts.append([sum(k == j for _, k, _ in base) for j in range(4)])
                base_sha.append(hashlib.sha256(",".join(names).encode()).hexdigest())
                if r in more:
                    part = data[offsets[r] : offsets[r + 1]]
                    point = np.concatenate([[0], np.cumsum((part & 0xC0) != 0x80)])
                    every = [(s, k, e, name) for (s, k, e), name in zip(base, names, strict=True)]
                    for s, e, label in more[r]:
                        s, e = added_spans(text, int(point[s - offsets[r]]), int(point[e - offsets[r]]), label)
                        if s < e and all(e <= a or b <= s for a, _, b, _ in every):
                            every.append((s, label - 1, e, f"{LABELS[label]}:{s}:{e}"))
                    names = [x[3] for x in sorted(every)]
                spans.append(",".join(names))
                n_spans.append(len(names))
            n = np.array(counts, np.int64).reshape(len(texts), 4)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(n[:, j]) for j in range(4)), pa.array(base_sha, pa.string()), pa.array(spans, pa.string()), pa.array(n_spans, pa.int64())], ["doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans", "n_spans"])

    return docs.select("doc_id", "text").mapInArrow(search, "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_spans long")
