"""Personal data: fixed patterns plus a character BiLSTM with CRF transitions, trained here in numpy.

The base patterns give spans that always stay.  The tagger reads overlapping windows of a
text (64 characters, a new one every 32), each decoded by Viterbi under learned
transitions; every character then takes its label from the window in which it is most
central, and the labels of the whole text are joined into spans.  A tagged span is added
if it fits its kind (``admissible``) and touches no span already held.  As an admissible
span has a digit, an ``@`` or an ``(at)`` inside, windows without any can't add one and aren't run.
What the tagger is there for are shapes beyond the base patterns: spelled-out addresses, phone
numbers without a plus, cards of 13 to 15 digits; it is trained on those too.

Edge cases: a null or empty text has no spans; repeated rows give repeated rows; ties
between base spans of different kinds all stay, since each kind is matched on its own;
columns other than ``doc_id`` and ``text`` are ignored by the query and kept by
:func:`redact`.  An empty table gives an empty table.  Positions are code points.
"""

from __future__ import annotations

import functools
import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import drop_suffix, read_documents, ship

KINDS = ("email", "ip", "card", "phone")
WINDOW, STRIDE = 64, 32
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
#: Starting inside a run of digits can't succeed where its start failed, so the look-behind changes nothing but the cost.
_IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]+\.[0-9]+\.[0-9]+")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
#: Addresses that are spelled out.
_SPELLED = re.compile(r"[A-Za-z0-9._%+-]+ ?[(\[]at[)\]] ?[A-Za-z0-9-]+(?: ?(?:[(\[]dot[)\]]|\.) ?[A-Za-z0-9-]+)+")
_HINT = re.compile(r"[0-9@]|[(\[]at[)\]]")
SCHEMA = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long"

Span = tuple[str, int, int]


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = int(d) * (1 + i % 2)
        total += n - 9 * (n > 9)
    return total % 10 == 0


def _digits(text: str) -> str:
    return "".join(c for c in text if "0" <= c <= "9")


def emails(text: str) -> list[tuple[int, int]]:
    """Leftmost non-overlapping matches in linear time: the local part is the run of its characters before an ``@``."""
    out, floor, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > floor and text[start - 1] in _LOCAL:
            start -= 1
        if start < at and (m := _DOMAIN.match(text, at)):
            out.append((start, m.end()))
            floor = m.end()
        at = text.find("@", at + 1)
    return out


def base_spans(text: str) -> list[Span]:
    """Spans of the fixed patterns, by kind as in KINDS and then start."""
    if not text or not _HINT.search(text):
        return []
    out: list[Span] = [("email", a, b) for a, b in emails(text)]
    out += [("ip", *m.span()) for m in _IP.finditer(text) if all(int(p[-20:]) <= 255 and len(p.lstrip("0")) <= 3 for p in m[0].split("."))]
    out += [("card", *m.span()) for m in _CARD.finditer(text) if 16 <= len(d := _digits(m[0])) <= 19 and luhn(d)]
    out += [("phone", *m.span()) for m in _PHONE.finditer(text) if 8 <= len(_digits(m[0])) <= 15]
    return out


def admissible(kind: str, found: str) -> bool:
    """Whether a tagged span can be personal data of its kind at all."""
    digits = _digits(found)
    if kind == "email" and "@" not in found:
        return _SPELLED.fullmatch(found) is not None
    if kind == "email":
        left, _, right = found.partition("@")
        return bool(left and right) and "." in right.strip(".") and not any(c.isspace() for c in found)
    if kind == "ip":
        parts = found.split(".")
        return len(parts) == 4 and all(p.isascii() and p.isdigit() and len(p) <= 3 and int(p) <= 255 for p in parts)
    if kind == "card":
        return 13 <= len(digits) <= 19 and luhn(digits)
    return 8 <= len(digits) <= 15 and set(found) <= set("+() .-0123456789") and found[0] in "+(0123456789" and len(found) - len(digits) >= 2 and len(found) <= 2 * len(digits)


def _alone(text: str, a: int, b: int) -> bool:
    """Neither letters nor digits touch the stretch."""
    return not (a and text[a - 1].isalnum()) and not (b < len(text) and text[b].isalnum())


# ---------------------------------------------------------------- the network

TAGS = ("O", *(f"{p}-{k}" for k in KINDS for p in "BI"))
_HIDDEN, _EMBED, _CHARS = 16, 12, 131


def char_ids(text: str) -> np.ndarray:
    """ASCII as it is plus one; 129 for other letters and digits, 130 for the rest; 0 is padding."""
    points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4").astype(np.int64)
    return np.where(points < 128, points + 1, np.where(points < 0x2000, 129, 130))


def _sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def _initial(rng: np.random.RandomState) -> dict[str, np.ndarray]:
    p = {"emb": rng.randn(_CHARS, _EMBED) * 0.3, "out": rng.randn(2 * _HIDDEN, len(TAGS)) * 0.2, "bias": np.zeros(len(TAGS)), "trans": np.zeros((len(TAGS), len(TAGS)))}
    for d in "fb":
        p[f"x{d}"] = rng.randn(_EMBED, 4 * _HIDDEN) / np.sqrt(_EMBED)
        p[f"h{d}"] = rng.randn(_HIDDEN, 4 * _HIDDEN) / np.sqrt(_HIDDEN)
        p[f"c{d}"] = np.concatenate([np.zeros(_HIDDEN), np.ones(_HIDDEN), np.zeros(2 * _HIDDEN)])
    return p


def _lstm(p, x, d, keep=False):
    """x: [time, batch, features] in reading order of direction d; returns the hidden states and what backward needs."""
    pre, h = x @ p[f"x{d}"] + p[f"c{d}"], np.zeros((x.shape[1], _HIDDEN))
    c, states, tape, n = np.zeros_like(h), np.empty((len(x), x.shape[1], _HIDDEN)), [], _HIDDEN
    for t in range(len(x)):
        z = pre[t] + h @ p[f"h{d}"]
        s, g = _sigmoid(z[:, : 3 * n]), np.tanh(z[:, 3 * n :])
        i, f, o = s[:, :n], s[:, n : 2 * n], s[:, 2 * n :]
        before, c = c, f * c + i * g
        squashed = np.tanh(c)
        if keep:
            tape.append((h, before, i, f, o, g, squashed))
        h = states[t] = o * squashed
    return states, tape


def _lstm_back(p, x, d, tape, dh_all, grad):
    n, dh, dc = _HIDDEN, 0.0, 0.0
    dz_all = np.empty((len(x), x.shape[1], 4 * n))
    for t in range(len(x) - 1, -1, -1):
        h, before, i, f, o, g, sq = tape[t]
        dh = dh + dh_all[t]
        dc = dc + dh * o * (1 - sq * sq)
        dz_all[t] = np.concatenate([dc * g * i * (1 - i), dc * before * f * (1 - f), dh * sq * o * (1 - o), dc * i * (1 - g * g)], 1)
        grad[f"h{d}"] += h.T @ dz_all[t]
        dh, dc = dz_all[t] @ p[f"h{d}"].T, dc * f
    grad[f"x{d}"] += np.einsum("tbe,tbz->ez", x, dz_all)
    grad[f"c{d}"] += dz_all.sum((0, 1))
    return dz_all @ p[f"x{d}"].T


def emissions(p, ids: np.ndarray):
    """ids: [batch, time] -> scores [time, batch, tags]."""
    x = p["emb"][ids.T]
    forward, _ = _lstm(p, x, "f")
    backward, _ = _lstm(p, x[::-1], "b")
    return np.concatenate([forward, backward[::-1]], 2) @ p["out"] + p["bias"]


def _lse(a, axis):
    top = a.max(axis, keepdims=True)
    return (np.log(np.exp(a - top).sum(axis, keepdims=True)) + top).squeeze(axis)


def _gradient(p, ids, tags):
    """Loss per character and gradient of the CRF's negative log-likelihood."""
    x = p["emb"][ids.T]
    hf, tf = _lstm(p, x, "f", True)
    hb, tb = _lstm(p, x[::-1], "b", True)
    hidden = np.concatenate([hf, hb[::-1]], 2)
    e, y = hidden @ p["out"] + p["bias"], tags.T
    steps, batch, k = e.shape
    alpha, beta = np.empty_like(e), np.zeros_like(e)
    alpha[0] = e[0]
    for t in range(1, steps):
        alpha[t] = e[t] + _lse(alpha[t - 1][:, :, None] + p["trans"], 1)
    for t in range(steps - 2, -1, -1):
        beta[t] = _lse(p["trans"][None] + (e[t + 1] + beta[t + 1])[:, None, :], 2)
    z = _lse(alpha[-1], 1)
    de = np.exp(alpha + beta - z[None, :, None])
    pairs = np.exp(alpha[:-1][:, :, :, None] + p["trans"] + (e[1:] + beta[1:])[:, :, None, :] - z[None, :, None, None])
    grad = {name: np.zeros_like(v) for name, v in p.items()}
    grad["trans"] = pairs.sum((0, 1))
    np.subtract.at(grad["trans"], (y[:-1].ravel(), y[1:].ravel()), 1)
    gold = np.take_along_axis(e, y[:, :, None], 2).sum() + p["trans"][y[:-1], y[1:]].sum()
    np.put_along_axis(de, y[:, :, None], np.take_along_axis(de, y[:, :, None], 2) - 1, 2)
    grad["out"] = hidden.reshape(-1, hidden.shape[2]).T @ de.reshape(-1, k)
    grad["bias"] = de.sum((0, 1))
    dh = de @ p["out"].T
    dx = _lstm_back(p, x, "f", tf, dh[:, :, :_HIDDEN], grad)
    dx = dx + _lstm_back(p, x[::-1], "b", tb, dh[::-1][:, :, _HIDDEN:], grad)[::-1]
    np.add.at(grad["emb"], ids.T, dx)
    return (z.sum() - gold) / e[:, :, 0].size, {n: g / batch for n, g in grad.items()}


def viterbi(p, ids: np.ndarray) -> np.ndarray:
    """The best tag sequence of each window: [batch, time]."""
    e = emissions(p, ids)
    score, back = e[0], np.empty(e.shape, np.int8)
    for t in range(1, len(e)):
        options = score[:, :, None] + p["trans"]
        back[t] = options.argmax(1)
        score = options.max(1) + e[t]
    out = np.empty(e.shape[:2], np.int64)
    out[-1] = score.argmax(1)
    for t in range(len(e) - 1, 0, -1):
        out[t - 1] = np.take_along_axis(back[t], out[t][:, None], 1)[:, 0]
    return out.T


def _draw(rng: np.random.RandomState) -> tuple[str, str | None]:
    """One labelled snippet, or an unlabelled one that looks like it."""
    pick = lambda s: s[rng.randint(len(s))]
    number = lambda n: "".join(str(rng.randint(10)) for _ in range(n))
    word = lambda: "".join(pick(("er", "on", "ti", "a", "sha", "ble", "ou", "in", "mar", "lo")) for _ in range(rng.randint(1, 4)))
    kind = rng.randint(9)
    if kind == 0 and rng.rand() < 0.5:
        at, dot = pick((("(at)", "(dot)"), ("[at]", "[dot]"), ("(at)", "."), ("[at]", ".")))
        gap = pick((" ", " ", ""))
        return f"{word()}{pick(('', '.', '_'))}{pick((word(), number(2)))}{gap}{at}{gap}{word()}{gap if dot != '.' else ''}{dot}{gap if dot != '.' else ''}{pick(('com', 'org', 'net'))}", "email"
    if kind < 2:
        return f"{word()}{pick(('', '.', '_', '+', '-'))}{pick((word(), number(2)))}@{word()}.{pick(('com', 'org', 'net', 'example.org', 'co.uk', 'test'))}", "email"
    if kind == 2:
        return ".".join(str(rng.randint(256)) for _ in range(4)), "ip"
    if kind == 3:
        body = number(15)
        digits = next(body + str(d) for d in range(10) if luhn(body + str(d)))
        if rng.rand() < 0.3:
            body = pick(("34", "37")) + number(12)
            digits = next(body + str(d) for d in range(10) if luhn(body + str(d)))
            return pick((" ", "-")).join((digits[:4], digits[4:10], digits[10:])), "card"
        return pick(("", " ", "-", ".")).join(digits[i : i + 4] for i in range(0, 16, 4)), "card"
    if kind == 4:
        return pick((f"{number(3)}-{number(3)}-{number(4)}", f"{number(3)}.{number(3)}.{number(4)}", f"00{number(2)} {number(2)} {number(4)} {number(3)}", f"0{number(3)} {number(3)} {number(4)}", f"+{number(2)} {number(3)} {number(4)} {number(3)}", f"+{number(1)}-{number(3)}-{number(3)}-{number(4)}", f"({number(3)}) {number(3)}-{number(4)}", f"+{number(2)} ({number(2)}) {number(4)}-{number(4)}")), "phone"
    return pick((number(rng.randint(1, 7)), f"{number(4)}-{number(2)}-{number(2)}", f"{number(2)}.{number(2)}", f"@{word()}", f"{word()} @ {word()}", f"v{number(1)}.{number(1)}.{number(1)}", f"{number(2)}:{number(2)}", f"{word()}{number(3)}", f"{number(3)},{number(3)}")), None


def labelled_windows(n: int, rng: np.random.RandomState) -> tuple[np.ndarray, np.ndarray]:
    """n training windows of invented prose with labelled spans."""
    ids, tags = np.zeros((n, WINDOW), np.int64), np.zeros((n, WINDOW), np.int64)
    syllables = ("er", "on", "ti", "an", "the", "of", "sha", "ble", "ou", "in", "é", "ñ", "eau", "st", "re")
    for row in range(n):
        text, marks = "", []
        while len(text) < WINDOW + 24:
            if rng.rand() < 0.3:
                snippet, kind = _draw(rng)
                if kind:
                    marks.append((len(text), len(text) + len(snippet), KINDS.index(kind)))
                text += snippet
            else:
                text += "".join(syllables[i] for i in rng.randint(0, len(syllables), rng.randint(1, 4)))
            text += (" ", " ", " ", ". ", ", ", "\n")[rng.randint(6)]
        cut = rng.randint(0, 24)
        ids[row] = char_ids(text)[cut : cut + WINDOW]
        line = np.zeros(len(text), np.int64)
        for a, b, k in marks:
            line[a:b], line[a] = 2 + 2 * k, 1 + 2 * k
        tags[row] = line[cut : cut + WINDOW]
    return ids, tags


@functools.lru_cache(maxsize=2)
def trained(steps: int = 260, batch: int = 48, seed: int = 11) -> dict[str, np.ndarray]:
    """Parameters after ``steps`` Adam steps on invented labelled windows; the same on every machine of a kind."""
    rng = np.random.RandomState(seed)
    p = _initial(rng)
    first, second = ({n: np.zeros_like(v) for n, v in p.items()} for _ in range(2))
    pool = labelled_windows(2400, rng)
    for step in range(1, steps + 1):
        rows = rng.randint(0, len(pool[0]), batch)
        _, grad = _gradient(p, pool[0][rows], pool[1][rows])
        norm = np.sqrt(sum((g * g).sum() for g in grad.values()))
        rate = 0.02 * min(1.0, 5 / norm) * (1 - step / (steps + 1)) ** 0.5
        for n, g in grad.items():
            first[n] = 0.9 * first[n] + 0.1 * g
            second[n] = 0.99 * second[n] + 0.01 * g * g
            p[n] = p[n] - rate * (first[n] / (1 - 0.9**step)) / (np.sqrt(second[n] / (1 - 0.99**step)) + 1e-8)
    return p


def window_starts(length: int) -> np.ndarray:
    """Every STRIDE characters, until the text's end is inside a window."""
    return np.arange(0, max(length - WINDOW + STRIDE, 1), STRIDE)


def tag_texts(p, texts: list[str]) -> list[list[Span]]:
    """Admissible tagged spans of each text, after reconciling its windows."""
    ids, where, found = [], [], [[] for _ in texts]
    for n, text in enumerate(texts):
        if not text or not _HINT.search(text):
            continue
        hints = np.fromiter((m.start() for m in _HINT.finditer(text)), np.int64)
        for start in window_starts(len(text)).tolist():
            at = np.searchsorted(hints, start)
            if at < len(hints) and hints[at] < start + WINDOW:
                piece = char_ids(text[start : start + WINDOW])
                ids.append(np.pad(piece, (0, WINDOW - len(piece))))
                where.append((n, start))
    if not ids:
        return found
    tags = np.concatenate([viterbi(p, np.stack(ids[i : i + 512])) for i in range(0, len(ids), 512)])
    central = np.minimum(np.arange(WINDOW), WINDOW - 1 - np.arange(WINDOW))
    at = 0
    while at < len(where):
        n, end = where[at][0], at
        while end < len(where) and where[end][0] == n:
            end += 1
        text = texts[n]
        label, rank = np.zeros(len(text), np.int64), np.full(len(text), -1)
        for w in range(at, end):
            start = where[w][1]
            size = min(WINDOW, len(text) - start)
            own = central[:size].copy()
            if start == 0:
                own[:STRIDE] = WINDOW
            if start + WINDOW >= len(text):
                own[STRIDE:] = WINDOW
            better = own > rank[start : start + size]
            label[start : start + size][better] = tags[w][:size][better]
            rank[start : start + size][better] = own[better]
        found[n] = _spans(text, label)
        at = end
    return found


def _spans(text: str, label: np.ndarray) -> list[Span]:
    kind = (label - 1) // 2
    fresh = (label > 0) & ((label % 2 == 1) | np.append(True, kind[1:] != kind[:-1]))
    out: list[Span] = []
    for a in np.flatnonzero(fresh).tolist():
        b = a + 1
        while b < len(text) and label[b] > 0 and kind[b] == kind[a] and not fresh[b]:
            b += 1
        name = KINDS[kind[a]]
        while b > a and text[b - 1] in " .,;:\n":
            b -= 1
        # A span's ends are those of the runs of digits, or of an address's characters, that it touches.
        inside = _LOCAL if name == "email" else "0123456789"
        while b > a > 0 and text[a - 1] in inside:
            a -= 1
        while a < b < len(text) and text[b] in inside and (text[b] != "." or text[b + 1 : b + 2].isalnum()):
            b += 1
        if b > a and _alone(text, a, b):
            # The network finds numbers well but can't count digits: a card of too few may be a phone number, and the other way round.
            fits = [k for k in ((name, "phone", "card") if name in ("phone", "card") else (name,)) if admissible(k, text[a:b])]
            out += [(k, a, b) for k in fits[:1]]
    return out


def find_spans(p, texts: list[str]) -> list[tuple[list[Span], list[Span]]]:
    """(base spans, all spans) of each text, both by kind and start."""
    out = []
    for text, tagged in zip(texts, tag_texts(p, texts), strict=True):
        base = base_spans(text)
        every = list(base)
        for kind, a, b in tagged:
            if all(b <= x or y <= a for _, x, y in every):
                every.append((kind, a, b))
        out.append((base, sorted(every, key=lambda s: (KINDS.index(s[0]), s[1]))))
    return out


def joined(spans: list[Span]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def masked(text: str, spans: list[Span]) -> str:
    """Each stretch of touching spans replaced by the upper-case kind of its first span in angle brackets."""
    out, end = [], 0
    for kind, a, b in sorted(spans, key=lambda s: (s[1], -s[2])):
        if a >= end:
            out += [text[end:a], f"<{kind.upper()}>"]
        end = max(end, b)
    return "".join([*out, text[end:]])


def _digest_rows(p):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = find_spans(p, [x or "" for x in batch.column(1).to_pylist()])
            counts = [pa.array([sum(s[0] == k for s in base) for base, _ in found], pa.int64()) for k in KINDS]
            digest = [hashlib.sha256(joined(base).encode()).hexdigest() for base, _ in found]
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), *counts, pa.array(digest, pa.string()), pa.array([joined(s) for _, s in found], pa.string()), pa.array([len(s) - len(b) for b, s in found], pa.int64())], [f.split()[0] for f in SCHEMA.split(", ")])

    return run


def tag_documents(docs: DataFrame, parameters: dict | None = None) -> DataFrame:
    """doc_id, counts of base spans by kind, digest of the base spans, all spans, and how many of them were added."""
    ship(docs.sparkSession)
    return drop_suffix(docs, ["doc_id", "text"]).mapInArrow(_digest_rows(parameters or trained()), SCHEMA)


def redact(docs: DataFrame, parameters: dict | None = None) -> DataFrame:
    """The same rows and columns, with every span of ``text`` masked; null texts stay null."""
    ship(docs.sparkSession)
    p, at = parameters or trained(), docs.columns.index("text")

    def run(batches):
        for batch in batches:
            texts = batch.column(at).to_pylist()
            found = find_spans(p, [x or "" for x in texts])
            new = pa.array([x if x is None else masked(x, s) for x, (_, s) in zip(texts, found, strict=True)], batch.schema.field(at).type)
            yield batch.set_column(at, batch.schema.field(at), new)

    return docs.mapInArrow(run, docs.schema)


def op4_pii_tagger(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tag_documents(read_documents(spark, sf_dir))
