"""Personal data: plain patterns, and a linear-chain conditional random field over word shapes.

The patterns' spans always stand. The field labels words around digits, at-signs and spelled-out
marks ('at', '(dot)' and the like, in any case, also inside a word), is trained on a small labelled
table by maximum likelihood, and is decoded by Viterbi over batches of windows; it
adds spans that the patterns can't express (phones without a plus, spelled-out addresses, and so on)
where they overlap no span of a pattern.
"""

from __future__ import annotations

import bisect
import hashlib
import ipaddress
import re
from array import array
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass
from functools import lru_cache, partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsecert.llm.common import load, slices

KINDS = ("email", "ip", "card", "phone")
#: Fixed patterns of the contract, parted where that keeps a search linear.
EMAIL_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
EMAIL_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
IP = re.compile(r"(?<![0-9])[0-9]+(?:\.[0-9]+){3}")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
DIGIT = re.compile(r"[0-9]")
SIGN = re.compile(r"[0-9@]")
WORD = re.compile(r"[^\x20\x09-\x0D]+")

_SPELLED = r"(?<![^\W\d_])(?:{})(?![^\W\d_])"
AT = re.compile(_SPELLED.format("at|arroba"), re.IGNORECASE)
#: A dot of an address; one before a blank ends a sentence.
DOT = re.compile(r"\.(?=\w)|(?<!\S)\.(?!\S)|" + _SPELLED.format("dot|punto"), re.IGNORECASE)
ANCHOR = re.compile(r"[0-9@]|" + _SPELLED.format("at|arroba|dot|punto"), re.IGNORECASE)

LABELS = ("O", *(f"{p}-{k}" for k in KINDS for p in "BI"))
CONTEXT = 4
CELLS = 1 << 16  # words of a batch of windows, filled up to the longest


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if i % 2 == 0 else d * 2 - 9 * (d > 4)
    return total % 10 == 0


def _digits(text: str) -> str:
    return "".join(c for c in text if "0" <= c <= "9")


def emails(text: str) -> list[tuple[int, int]]:
    """Around each at-sign: the local part ends right before it, the domain begins right after."""
    out, free, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > free and text[start - 1] in EMAIL_LOCAL:
            start -= 1
        # what failed at this at-sign can't be part of a later local part beyond it
        m = EMAIL_DOMAIN.match(text, at + 1) if start < at else None
        if m:
            out.append((start, m.end()))
            free = m.end()
            at = text.find("@", free)
        else:
            free = at + 1
            at = text.find("@", at + 1)
    return out


def plain_spans(text: str) -> list[tuple[int, int, int]]:
    """(kind, start, end) by kind, then start."""
    out = [(0, s, e) for s, e in emails(text)] if "@" in text else []
    if DIGIT.search(text):
        if "." in text:
            out += [(1, m.start(), m.end()) for m in IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m.group().split("."))]
        for m in CARD.finditer(text):
            if m.end() - m.start() >= 13 and 13 <= len(d := _digits(m.group())) <= 19 and luhn(d):
                out.append((2, m.start(), m.end()))
        if "+" in text:
            out += [(3, m.start(), m.end()) for m in PHONE.finditer(text) if 9 <= len(_digits(m.group())) <= 15]
    return out


# ---- the field


_SIGNS = "@.+-()[]:/_,#%$€=|"


class _Kinds(dict):
    """The kind of each sign, found once."""

    def __missing__(self, c: int) -> str:
        sign = chr(c)
        self[c] = k = "d" if "0" <= sign <= "9" else "X" if sign.isupper() else "x" if sign.isalpha() else sign if sign in _SIGNS else "?"
        return k


_KINDS = _Kinds()
REPEATED = re.compile(r"([^d])\1+|(d{5})d+")


def shape(word: str) -> str:
    """Letters, digits and other signs of a word; runs of letters shrink, runs of digits keep their length up to 5."""
    return REPEATED.sub(lambda m: m[1] or m[2], word.translate(_KINDS))


CUES = {w: "tel" for w in "tel phone call mobile cell fax telefon tél teléfono whatsapp sms dial".split()} | {w: "mail" for w in "mail email e-mail contact write correo".split()} | {w: "net" for w in "ip host server address addr ping".split()} | {w: "card" for w in "card visa mastercard amex kreditkarte carte tarjeta".split()} | {w: "other" for w in "price total version page order isbn date id invoice room year chapter section".split()}


TOPS = tuple("com org net info edu gov io eu de es fr it uk nl ch".split())
BRACKETED = re.compile(r"[(\[](?:at|dot)[)\]]", re.IGNORECASE)


def mark(word: str) -> str:
    """The spelled-out mark that a word is or holds, in either case."""
    at, dot = AT.search(word), DOT.search(word)
    if not (at or dot) or "@" in word:
        return "-"
    alone = (at or dot).group().lower() == word.lower().strip(".,;:!?()[]\"'")
    form = "alone " if alone else "in a word "
    form += "in brackets " if BRACKETED.search(word) else ""
    return form + ("both" if at and dot else "at" if at else "dot" if dot.group() != "." else ".")


def word_features(word: str) -> tuple[str, ...]:
    return _short_features(word) if len(word) <= 64 else _features(word)


@lru_cache(maxsize=65536)
def _short_features(word: str) -> tuple[str, ...]:
    return _features(word)


def _features(word: str) -> tuple[str, ...]:
    low = word.lower().strip(".,;:!?()[]\"'")
    digits = len(DIGIT.findall(word))
    form = word.lower() if BRACKETED.search(word) else word
    return (f"s={shape(form)}", f"t={shape(form.strip('.,;:!?'))}", f"n={min(digits, 20)}", f"a={'@' in word}", f"c={CUES.get(low, '-')}", f"w={low if low in CUES else 'top' if low in TOPS else mark(word)}")


def features(words: list[str], i: int) -> list[str]:
    out = list(word_features(words[i]))
    for d in (-2, -1, 1, 2):
        j = i + d
        if 0 <= j < len(words):
            f = word_features(words[j])
            out += [f"{d}{f[1]}", f"{d}{f[4]}", f"{d}{f[5]}"]
        else:
            out.append(f"{d}edge")
    return out


def labelled_table(copies: int = 6, seed: int = 7) -> list[tuple[list[str], list[str]]]:
    """The small labelled table: sentences with spans, written here, filled with drawn values.

    In a template, {kind} stands for a value of that kind and all its words are labelled.
    """
    draw = np.random.default_rng(seed)
    d = lambda n: "".join(str(x) for x in draw.integers(0, 10, n))
    w = lambda: "".join(draw.choice(list("aeioulnrst"), int(draw.integers(3, 8))))
    pick = lambda *x: x[int(draw.integers(len(x)))]()
    one = lambda *x: x[int(draw.integers(len(x)))]

    def spelled(one_word: bool = False) -> str:
        """A spelled-out address, as words or as one word with bracketed marks; letters may be of either case."""
        at, dot = one(*[("(at)", "."), ("[at]", "."), ("(at)", "(dot)"), ("[at]", "[dot]")]) if one_word else one(("at", "dot"), ("at", "dot"), ("(at)", "(dot)"), ("[at]", "[dot]"), ("(at)", "."), ("[at]", "."), ("arroba", "punto"))
        gap = "" if one_word else " "
        join = "." if dot == "." else f"{gap}{dot}{gap}"
        name, host = join.join(w() for _ in range(one(1, 1, 1, 2))), join.join([w() for _ in range(one(1, 1, 1, 2))] + [one("com", one(*TOPS))])
        return one(str, str, str.upper, str.title)(f"{name}{gap}{at}{gap}{host}") if one(0, 0, 0, 1) == 0 else f"{name}{gap}{at.upper()}{gap}{host}"

    octet = lambda: str(int(draw.integers(1, 255)))
    values = {
        "phone": lambda: pick(lambda: f"({d(3)}) {d(3)}-{d(4)}", lambda: f"{d(3)}-{d(3)}-{d(4)}", lambda: f"{d(3)}.{d(3)}.{d(4)}", lambda: f"+1 ({d(3)}) {d(3)}-{d(4)}", lambda: f"+{d(2)} {d(3)} {d(3)} {d(3)}", lambda: f"1-{d(3)}-{d(3)}-{d(4)}"),
        "email": lambda: pick(lambda: f"{w()}.{w()}@{w()}.com", lambda: f"{w()}@{w()}.example.org", lambda: f"{w()} at {w()} dot com", lambda: f"{w()} (at) {w()} (dot) org", lambda: f"{w()}{d(2)} [at] {w()} [dot] net", *[spelled] * 4, *[lambda: spelled(True)] * 4),
        "ip": lambda: pick(lambda: ".".join(octet() for _ in range(4)), lambda: f"2001:db8:{d(4)}::{d(2)}", lambda: f"fe80::{d(4)}:{d(4)}"),
        "card": lambda: f"{d(4)} {d(4)} {d(4)} {d(4)}",
        "num": lambda: pick(lambda: d(int(draw.integers(1, 6))), lambda: f"{d(2)}.{d(2)}", lambda: f"{d(1)},{d(3)}", lambda: f"${d(3)}.{d(2)}", lambda: f"{d(2)}%"),
        "date": lambda: pick(lambda: f"20{d(2)}-{d(2)}-{d(2)}", lambda: f"{d(2)}/{d(2)}/20{d(2)}", lambda: f"{d(2)}:{d(2)}", lambda: f"{d(2)}.{d(2)}.20{d(2)}"),
        "code": lambda: pick(lambda: d(16), lambda: f"v{d(1)}.{d(2)}.{d(1)}", lambda: f"978-{d(1)}-{d(4)}-{d(4)}-{d(1)}", lambda: d(13), lambda: f"#{d(5)}", lambda: f"{w()}{d(3)}", lambda: hashlib.md5(d(8).encode()).hexdigest(), lambda: f"@{w()}{d(2)}", lambda: f"{d(3)}-{d(4)}", lambda: f"{d(2)}-{d(4)}"),
        "w": w,
    }
    templates = [
        "call me on {phone} {w} {w}", "{w} phone {phone} or {w}", "tel: {phone} , {w}", "{w} {w} {phone} {w} {w}", "fax {phone}", "{w} mail {email} {w}", "contact {email} for {w}", "{w} {w} {email} {w} {w}", "write to {email}",
        "host {ip} {w} {w}", "{w} {ip} {w}", "server address {ip} is {w}", "card {card} {w}", "visa {card}", "{w} {w} {card} {w}", "{w} {num} {w} {w}", "price {num} {w}", "the {w} of {date} was {w}", "{w} {date} {w} {num}", "order id {code} {w}",
        "{w} {w} {code} {w} {w}", "version {code} of {w}", "{w} {code} {w} {num}", "page {num} {w} {w}", "{w} {w} {w} {w}", "meet me at {w} street {num}", "{w} at {num} {w}", "isbn {code}", "{code} {w} {w}", "{w} {w} {code}", "{num} {num} {num}", "{w} at the {w} {num} {w}", "token = {code} {w}",
        "{w} {w} at {w} {w} {w}", "{w} at {w}. {w} {w}", "{w} {w} at the {w} of {w}.", "{w} {w} dot {w} {w}", "{w} dot at the {w} {w}", "{w}, {w} at {w} and {w}", "look at {w}", "a dot on {w} {w}", "{w} {email} {w} at {w} {w}", "{w} {w} {w}. at {w} {w}", "{w} at {w}", "{w} {w} (at) {w} {w}", "{w} at {w} dot {w} {w} {w}", "{w} {w} at the dot {w} {w}",
        "{w} {w} at {w}.com {w} {w}", "{w} at {w}.org, {w}", "{w} {w} {email} or {w} {w}", "{w} to {email} please", "{w}: {email} and {w}", "{email}", "{email} {w} {w}", "{w} {w} {w} {email}", "{w} {email}. {w}", "{w} us: {email} or {w} {w}", "({email})",
    ]
    table = []
    for template in templates * copies:
        words, labels = [], []
        for part in template.split():
            # signs may stand before and after the braces
            before, _, rest = part.partition("{")
            name, _, after = rest.partition("}")
            got = (before + (values[name]() if name else "") + after).split()
            words += got
            labels += [f"{'I' if i else 'B'}-{name}" if name in KINDS else "O" for i in range(len(got))]
        table.append((words, labels))
    return table


class Field:
    """Weights of a linear-chain field: emissions by feature, transitions, and where a path may start."""

    def __init__(self, names: dict[str, int], emit: np.ndarray, step: np.ndarray):
        self.names, self.emit, self.step = names, emit, step

    def scores(self, windows: list[list[str]]) -> tuple[np.ndarray, np.ndarray]:
        length = max(map(len, windows))
        out, mask = np.zeros((len(windows), length, len(LABELS))), np.zeros((len(windows), length), dtype=bool)
        for n, words in enumerate(windows):
            for i in range(len(words)):
                out[n, i] = self.score(words, i)
            mask[n, : len(words)] = True
        return out, mask

    def score(self, words: list[str], i: int) -> np.ndarray:
        at = [self.names[f] for f in features(words, i) if f in self.names]
        return self.emit[at].sum(axis=0)

    def decode(self, windows: list[list[str]]) -> list[np.ndarray]:
        """Viterbi over a batch of windows, all of its steps on arrays of (window, label, label)."""
        scores, mask = self.scores(windows)
        count, length, width = scores.shape
        best, back = scores[:, 0].copy(), np.zeros((count, length, width), dtype=np.uint8)
        for t in range(1, length):
            paths = best[:, :, None] + self.step[None]
            back[:, t] = paths.argmax(axis=1)
            best = np.where(mask[:, t, None], paths.max(axis=1) + scores[:, t], best)
        out = []
        for n, words in enumerate(windows):
            path = [int(best[n].argmax())]
            for t in range(len(words) - 1, 0, -1):
                path.append(int(back[n, t, path[-1]]))
            out.append(np.array(path[::-1]))
        return out

    def decode_long(self, word: Callable[[int], str], length: int, stretch: int = 1 << 14) -> np.ndarray:
        """The best path of one window of any length, the same that decode finds.

        Scores are made stretch by stretch and words are read where they are needed, so that one byte
        a word and label is all that is held.
        """
        width = len(LABELS)
        back, best = np.zeros((length, width), dtype=np.uint8), None
        for low in range(0, length, stretch):
            first, stop = max(0, low - 2), min(length, low + stretch)
            words = [word(i) for i in range(first, min(length, stop + 2))]  # two words on each side have a say in a word's score
            for i in range(low, stop):
                at = i - first
                mine = self.score(words, at)
                if best is None:
                    best = mine
                    continue
                paths = best[:, None] + self.step
                back[i] = paths.argmax(axis=0)
                best = paths.max(axis=0) + mine
        path = np.zeros(length, dtype=np.uint8)
        path[-1] = best.argmax()
        for t in range(length - 1, 0, -1):
            path[t - 1] = back[t, path[t]]
        return path


#: A label I-k follows only B-k or I-k.
FORBIDDEN = np.array([[-1e4 if b[0] == "I" and a[1:] != b[1:] else 0.0 for b in LABELS] for a in LABELS])


def train(table: list[tuple[list[str], list[str]]], steps: int = 120, ridge: float = 0.02, rate: float = 0.1) -> Field:
    """Maximum likelihood with a ridge; gradients by forward and backward sums over the padded table."""
    names: dict[str, int] = {}
    found = [[[names.setdefault(f, len(names)) for f in features(words, i)] for i in range(len(words))] for words, _ in table]
    count, length, width = len(table), max(len(w) for w, _ in table), len(LABELS)
    gold = np.full((count, length), -1)
    for n, (_, labels) in enumerate(table):
        gold[n, : len(labels)] = [LABELS.index(x) for x in labels]
    mask = gold >= 0
    rows = np.array([(n * length + i, f) for n, s in enumerate(found) for i, at in enumerate(s) for f in at])
    emit, step = np.zeros((len(names), width)), np.zeros((width, width))
    moments = [[np.zeros_like(x), np.zeros_like(x)] for x in (emit, step)]
    hot = np.eye(width)[np.where(mask, gold, 0)] * mask[..., None]
    for it in range(1, steps + 1):
        scores = np.zeros((count * length, width))
        np.add.at(scores, rows[:, 0], emit[rows[:, 1]])
        scores = scores.reshape(count, length, width)
        moves = step + FORBIDDEN
        ahead, behind = [scores[:, 0]], [np.zeros((count, width))]
        top = lambda x, axis: (m := x.max(axis=axis, keepdims=True)).squeeze(axis) + np.log(np.exp(x - m).sum(axis=axis))
        for t in range(1, length):
            ahead.append(np.where(mask[:, t, None], top(ahead[-1][:, :, None] + moves, 1) + scores[:, t], ahead[-1]))
        for t in range(length - 1, 0, -1):
            behind.insert(0, np.where(mask[:, t, None], top(moves[None] + (scores[:, t] + behind[0])[:, None, :], 2), behind[0]))
        total = top(ahead[-1], 1)
        share = np.exp(np.stack(ahead, 1) + np.stack(behind, 1) - total[:, None, None]) * mask[..., None]
        error = (share - hot).reshape(count * length, width)
        g_emit = np.zeros_like(emit)
        np.add.at(g_emit, rows[:, 1], error[rows[:, 0]])
        g_step = np.zeros_like(step)
        for t in range(1, length):
            pair = np.exp(ahead[t - 1][:, :, None] + moves + (scores[:, t] + behind[t])[:, None, :] - total[:, None, None]) * mask[:, t, None, None]
            g_step += pair.sum(axis=0) - hot[:, t - 1].T @ hot[:, t]
        for x, g, (m, v) in zip((emit, step), (g_emit / count + ridge * emit / count, g_step / count + ridge * step / count), moments, strict=True):
            m += 0.1 * (g - m)
            v += 0.001 * (g * g - v)
            x -= rate * (m / (1 - 0.9**it)) / (np.sqrt(v / (1 - 0.999**it)) + 1e-8)
    return Field(names, emit, step + FORBIDDEN)


@dataclass(frozen=True, slots=True)
class Place:
    """Where a word stands in its text."""

    low: int
    high: int

    def start(self) -> int:
        return self.low

    def end(self) -> int:
        return self.high


class Window(Sequence):
    """Words in a row, held as starts and ends in turn: 16 bytes a word, so that long ones stay small."""

    __slots__ = ("ends",)

    def __init__(self, ends: array):
        self.ends = ends

    def __len__(self) -> int:
        return len(self.ends) // 2

    def __getitem__(self, i: int) -> Place:
        if not -len(self) <= i < len(self):
            raise IndexError(i)
        i %= len(self)
        return Place(self.ends[2 * i], self.ends[2 * i + 1])

    def word(self, text: str, i: int) -> str:
        return text[self.ends[2 * i] : self.ends[2 * i + 1]]

    def words(self, text: str) -> list[str]:
        return [self.word(text, i) for i in range(len(self))]


def windows_of(text: str) -> Iterator[Window]:
    """Stretches of words around those with a digit, an at-sign or a spelled-out mark, CONTEXT words on each side."""
    held, gap = array("q"), array("q")
    for m in WORD.finditer(text):
        if ANCHOR.search(text, m.start(), m.end()):
            held += gap
            held.extend(m.span())
            gap = array("q")
            continue
        gap.extend(m.span())
        if held and len(gap) > 4 * CONTEXT:
            yield Window(held + gap[: 2 * CONTEXT])
            held = array("q")
        if not held:
            gap = gap[-2 * CONTEXT :]
    if held:
        yield Window(held + gap[: 2 * CONTEXT])


EDGES = ".,;:!?\"'|<>{}*#$%&"


def _checked(kind: str, text: str) -> bool:
    """What a span of the field must hold besides its label."""
    digits = _digits(text)
    if kind == "phone":
        return 9 <= len(digits) <= 15 and not re.search(r"[A-Za-z@:/]", text)
    if kind == "card":
        return 13 <= len(digits) <= 19 and luhn(digits)
    if kind == "ip":
        try:
            ipaddress.ip_address(text)
        except ValueError:
            return False
        return True
    if not re.search(r"[A-Za-z]", text):
        return False
    if "@" in text:
        return "." in text or bool(DOT.search(text))
    at = AT.search(text)
    return bool(at and DOT.search(text, at.end()))


def _may_add(text: str, window: Window, covered: Covered) -> bool:
    """Whether a span of the field can come of a window: of a digit or an at-sign outside the patterns' spans, or of both spelled-out marks."""
    for w in window:
        if SIGN.search(text, w.low, w.high) and not covered.meets(w.low, w.high):
            return True
    end = window[-1].high
    at = AT.search(text, window[0].low, end)
    return bool(at and DOT.search(text, at.end(), end))


def spans_of(text: str, window: Window, path: np.ndarray) -> Iterator[tuple[int, int, int]]:
    i = 0
    while i < len(path):
        label = LABELS[path[i]]
        if label[0] != "B":
            i += 1
            continue
        j = i + 1
        while j < len(path) and LABELS[path[j]] == f"I{label[1:]}":
            j += 1
        start, end = window[i].low, window[j - 1].high
        while start < end and text[start] in EDGES:
            start += 1
        while end > start and text[end - 1] in EDGES:
            end -= 1
        if _checked(label[2:], text[start:end]):
            yield KINDS.index(label[2:]), start, end
        i = j


def joined(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for k, s, e in spans)


class Covered:
    """The places that spans cover, as stretches in order, for searches by bisection."""

    def __init__(self, spans: list[tuple[int, int, int]]):
        self.starts: list[int] = []
        self.ends: list[int] = []
        for s, e in sorted((s, e) for _, s, e in spans):
            if self.ends and s < self.ends[-1]:
                self.ends[-1] = max(self.ends[-1], e)
            else:
                self.starts.append(s)
                self.ends.append(e)

    def meets(self, start: int, end: int) -> bool:
        i = bisect.bisect_right(self.ends, start)
        return i < len(self.starts) and self.starts[i] < end


def find_personal(field: Field, texts: list[str]) -> list[tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]]:
    """For each text, the patterns' spans and all spans, by kind, then start."""
    base = [plain_spans(t) for t in texts]
    covered = [Covered(b) for b in base]
    extra: list[list[tuple[int, int, int]]] = [[] for _ in texts]

    def told(n: int, window: Window, path: np.ndarray) -> None:
        extra[n].extend(s for s in spans_of(texts[n], window, path) if not covered[n].meets(s[1], s[2]))

    def solve(held: list[tuple[int, Window]]) -> None:
        """Windows of like length share a batch of at most CELLS words, filled up to its longest."""
        held.sort(key=lambda x: len(x[1]))
        i = 0
        while i < len(held):
            j = i + 1
            while j < len(held) and j - i < 256 and (j - i + 1) * len(held[j][1]) <= CELLS:
                j += 1
            for (n, window), path in zip(held[i:j], field.decode([w.words(texts[n]) for n, w in held[i:j]]), strict=True):
                told(n, window, path)
            i = j

    held, words = [], 0
    for n, text in enumerate(texts):
        if not ANCHOR.search(text):
            continue
        for window in windows_of(text):
            if not _may_add(text, window, covered[n]):
                continue
            if len(window) > CELLS // 4:
                told(n, window, field.decode_long(partial(window.word, text), len(window)))
                continue
            held.append((n, window))
            words += len(window)
            if words > CELLS:  # what is held at a time has a bound, whatever the texts hold
                solve(held)
                held, words = [], 0
    solve(held)
    return [(b, sorted({*b, *e})) for b, e in zip(base, extra, strict=True)]


def scan_documents(docs: DataFrame, field: Field | None = None, text: str = "text", key: str = "doc_id") -> DataFrame:
    """One row per row of docs: counts and digest of the patterns' spans, and all spans.

    Null texts count as empty; ids may be null or repeat; an empty table gives an empty result;
    further columns of docs are ignored.
    """
    model = field or train(labelled_table())
    names = ["doc_id", *(f"n_{k}" for k in KINDS), "base_sha256", "spans"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "_text", rows=512):
            found = find_personal(model, batch.column("_text").to_pylist())
            counts = [pa.array([sum(1 for s in b if s[0] == k) for b, _ in found], pa.int64()) for k in range(4)]
            digests = pa.array([hashlib.sha256(joined(b).encode()).hexdigest() for b, _ in found], pa.string())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *counts, digests, pa.array([joined(e) for _, e in found], pa.string())], names=names)

    narrow = docs.select(F.col(key).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("_text"))
    kind = narrow.schema["doc_id"].dataType.simpleString()
    return narrow.mapInArrow(run, f"doc_id {kind}, " + ", ".join(f"n_{k} bigint" for k in KINDS) + ", base_sha256 string, spans string")


def op6_crf_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_documents(load(spark, sf_dir, "documents"))
