"""Personal data: base patterns, and a linear-chain conditional random field that adds spans.

Base spans, leftmost and non-overlapping within a kind, by the patterns of ``BASE``; a match that fails its check is
dropped and not tried again. On top, a linear-chain CRF labels every word of every line (``none``, a kind, or ``secret``) from word-shape features; it is trained by full-batch gradient steps on a small labelled
table, and decoded by Viterbi, all lines of a batch at once in numpy. Runs of
words of one kind become spans (outer punctuation trimmed) if they pass the kind's check and touch no base
span: the CRF finds what the patterns miss, such as spelled-out mail addresses, telephone numbers without a
plus sign, version 6 addresses, and secrets (tokens, keys and passwords that are assigned to a name).

The labelled table has two sources (``labelled_rows``): lines of invented words, and lines of the words of a bounded sample of the documents (``context_words``);
into either, invented personal data, secrets and harmless look-alikes are set.

Edge cases: a null text is an empty one and has no spans; very long texts and lines are decoded whole, features run by run of ``SLICE_BYTES``;
where two kinds match at one place both base spans stay, in the order of the kinds; of tied label paths the earlier label is taken;
repeated rows get the same answer; an empty table gives no rows; further columns pass through ``find``, and columns named ``base`` or ``spans`` are replaced.
"""

from __future__ import annotations

import hashlib
import random
import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import lower_ascii, span_hashes, table, text_slices, without, word_runs, word_spans

KINDS = ("email", "ip", "card", "phone")
#: What the CRF alone adds.
SECRET = "secret"
LABELS = ("none", *KINDS, SECRET)
#: The base patterns.
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
BASE = {
    # runs of digits are taken whole or not at all: the same matches, in linear time
    "ip": re.compile(r"(?<![0-9])[0-9]++(\.[0-9]++)(\.[0-9]++)(\.[0-9]++)"),
    "card": re.compile(r"[0-9]([\x20-]?[0-9])+"),
    "phone": re.compile(r"\+[0-9][\x20().0-9-]+[0-9]"),
}
_NOT_DIGIT = re.compile(r"[^0-9]+")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def _holds(kind: str, text: str) -> bool:
    """Whether a match of a base pattern passes its check."""
    if kind == "ip":
        return all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in text.split("."))
    digits = _NOT_DIGIT.sub("", text)
    return 12 <= len(digits) <= 19 and luhn(digits) if kind == "card" else 9 <= len(digits) <= 15


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) in code points, sorted."""
    out, last, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > last and text[start - 1] in LOCAL:
            start -= 1
        found = DOMAIN.match(text, at + 1) if start < at else None
        if found:
            out.append((start, 0, found.end()))
            last = found.end()
        at = text.find("@", max(at + 1, last))
    for k, kind in enumerate(KINDS[1:], 1):
        if kind != "phone" or "+" in text:
            out += [(m.start(), k, m.end()) for m in BASE[kind].finditer(text) if _holds(kind, m.group())]
    return sorted(out)


# ---- the labelled table

_GIVEN = ("anna", "ben", "carla", "david", "emma", "felix", "greta", "hugo", "ines", "jonas", "klara", "luis", "maria", "nils", "olga", "paul", "rosa", "sam", "tina", "viktor")
_HOSTS = ("example", "mail", "post", "acme", "web", "uni", "shop", "corp")
_ENDS = ("com", "org", "net", "de", "fr", "es")
_PLAIN = "the of and to in is that it was for on with as by at or from this be an are dot mail call write see page line note der die und la le que el los de en".split()


_NAMES = ("token", "api_key", "apikey", "secret", "password", "passwd", "auth_token", "access_key", "client_secret", "private_key")
_ALNUM = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"


def _secret(rng: random.Random) -> tuple[str, int]:
    """An assignment, and how many of its words come before the secret."""
    kind = rng.randrange(3)
    value = f"{rng.randrange(1 << 160):040x}" if kind == 0 else f"{rng.randrange(1 << 128):032x}" if kind == 1 else "".join(rng.choice(_ALNUM) for _ in range(rng.randint(20, 44)))
    quote = rng.choice(('"', '"', "'", ""))
    name, sign = rng.choice(_NAMES), rng.choice(("=", "=", ":"))
    return (f"{name} {sign} {quote}{value}{quote}", 2) if rng.random() < 0.7 else (f"{name}{sign} {quote}{value}{quote}", 1)


def _spoken(rng: random.Random) -> tuple[str, str, int]:
    """(kind, text, words before the span)."""
    d = lambda n: "".join(rng.choice("0123456789") for _ in range(n))
    kind = rng.choice(("spell", "bracket", "paren", "short", "phone", "phone2", "phone3", "phone4", "six", "card", "secret", "secret"))
    who = rng.choice(_GIVEN) + rng.choice(("", f".{rng.choice(_GIVEN)}", d(2)))
    host, end = rng.choice(_HOSTS) + rng.choice(("", d(1))), rng.choice(_ENDS)
    if kind == "secret":
        return SECRET, *_secret(rng)
    if kind == "six":
        return "ip", ":".join(f"{rng.randrange(1 << 16):x}" for _ in range(rng.choice((8, 6)))).replace(":0:", "::"), 0
    if kind == "card":
        digits = "4" + d(14)
        digits += next(c for c in "0123456789" if luhn(digits + c))
        return "card", ".".join(digits[i : i + 4] for i in range(0, 16, 4)), 0
    mails = {"spell": f"{who} at {host} dot {end}", "bracket": f"{who} [at] {host} [dot] {end}", "paren": f"{who}(at){host}.{end}", "short": f"{who}[at]{host}[dot]{end}"}
    phones = {"phone": f"({d(3)}) {d(3)}-{d(4)}", "phone2": f"{d(3)}-{d(3)}-{d(4)}", "phone3": f"0{d(3)}/{d(7)}", "phone4": f"{d(3)}.{d(3)}.{d(4)}"}
    return ("email", mails[kind], 0) if kind in mails else ("phone", phones[kind], 0)


def _harmless(rng: random.Random) -> str:
    d = lambda n: "".join(rng.choice("0123456789") for _ in range(n))
    return rng.choice((
        d(4), d(2), d(1), d(rng.randint(12, 19)), f"{d(1)}.{d(2)}", f"{d(4)}-{d(2)}-{d(2)}", f"{d(2)}:{d(2)}", f"${d(3)}.{d(2)}", f"{d(3)}%", f"v{d(1)}.{d(1)}.{d(2)}",
        f"commit {rng.randrange(1 << 160):040x}", f"id {rng.randrange(1 << 64):016x}", f"md5 {rng.randrange(1 << 128):032x}", f"({d(4)})", f"{d(1)}-{d(1)}", "look at the shop dot", "at home (at) last", f"page {d(3)}", f"https://{rng.choice(_HOSTS)}.{rng.choice(_ENDS)}/{d(4)}",
        f"{rng.choice(_PLAIN)}###", f"{rng.choice(_PLAIN).upper()}!!", "|", f"{d(3)},{d(3)}", f"{rng.choice(_NAMES)} = {rng.choice(_PLAIN)}", "the token is in the box", f"a password of {d(1)} words", f"{rng.choice(_PLAIN)} = {d(4)}",
    ))


def labelled_rows(count: int = 1_000, seed: int = 7, contexts: list[str] | None = None) -> list[tuple[str, list[str]]]:
    """(text, label of each word): lines of which about half hold personal data or secrets; every other line has its plain words from ``contexts``."""
    rng, rows = random.Random(seed), []
    for n in range(count):
        words, labels = [], []
        for _ in range(rng.randint(1, 4)):
            for _ in range(rng.randint(0, 6)):
                if contexts and n % 2:
                    words.append(rng.choice(contexts))
                else:
                    w = rng.choice(_PLAIN) if rng.random() < 0.6 else "".join(rng.choice("abcdefghilmnoprstuv") for _ in range(rng.randint(2, 12)))
                    words.append((w.capitalize() if rng.random() < 0.2 else w.upper() if rng.random() < 0.05 else w) + rng.choice(("", "", "", "", ",", ".")))
                labels.append("none")
            kind, text, before = _spoken(rng) if rng.random() < 0.4 else ("none", _harmless(rng), 0)
            words += (text + rng.choice(("", "", ".", ","))).split()
            labels += ["none"] * before
            labels += [kind] * (len(words) - len(labels))
        rows.append((" ".join(words), labels))
    return rows


#: Documents whose words are the context of half of the labelled lines, and the characters that are read of each: a bounded sample, for training only.
CONTEXT_DOCS, CONTEXT_CHARS = 100, 2_000


def context_words(docs: DataFrame) -> list[str]:
    """Plain words (no digit, no mark of an address) of a bounded sample of the documents, chosen by a hash of the id."""
    unit, parts = 1 << 30, max(1, docs.count())
    key = F.pmod(F.xxhash64(F.lit(3), "doc_id"), F.lit(unit))
    # about four documents for each that is wanted pass, so tasks send next to nothing; of those of one slot, the first
    few = docs.where(F.col("doc_id").isNotNull() & F.col("text").isNotNull() & (key < F.lit(max(1, 4 * CONTEXT_DOCS * unit // parts))))
    slots = few.groupBy((key % CONTEXT_DOCS).alias("slot")).agg(F.min(F.struct(key.alias("key"), F.substring("text", 1, CONTEXT_CHARS).alias("text")))["text"].alias("text"))
    some = slots.collect()  # at most CONTEXT_DOCS rows
    return sorted({w for r in some for w in r.text.split() if not re.search(r"[0-9@+=]", w) and len(w) < 30})


def labelled_table(spark: SparkSession, count: int = 1_000, seed: int = 7, contexts: list[str] | None = None) -> DataFrame:
    return spark.createDataFrame(labelled_rows(count, seed, contexts), "text string, labels array<string>")


# ---- features

_CLASS = np.array([1 if 65 <= c <= 90 else 2 if 97 <= c <= 122 or c >= 128 else 3 if 48 <= c <= 57 else c for c in range(256)], np.uint8)
_COARSE = 12
_DIGIT = np.array([48 <= c <= 57 for c in range(256)])
_ALPHA = np.array([65 <= c <= 90 or 97 <= c <= 122 or c >= 128 for c in range(256)])
_MARK = np.array([chr(c) in "@:/[]()+-." and c < 128 for c in range(256)])


def _counts(flags: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    total = np.zeros(len(flags) + 1, np.int32)
    np.cumsum(flags, out=total[1:])
    return total[ends] - total[starts]


def _looks(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of each word: hash of its shape, hash of its lower-cased spelling, coarse class, bucket of its digits."""
    found = []
    for i, j, lo, hi in word_runs(starts, ends):
        part, first, last = buf[lo:hi], starts[i:j] - lo, ends[i:j] - lo
        kinds = _CLASS[part]
        lead = np.ones(len(part), bool)
        lead[1:] = kinds[1:] != kinds[:-1]
        lead[first] = True
        runs = np.flatnonzero(lead)
        shape = span_hashes(kinds[runs], np.searchsorted(runs, first), np.searchsorted(runs, last))
        digits, letters, marks = (_counts(f[part], first, last) for f in (_DIGIT, _ALPHA, _MARK))
        coarse = (digits > 0) * 6 + (letters > 0) * 3 + np.minimum(marks, 2)
        bucket = np.searchsorted(np.array([1, 2, 3, 4, 5, 7, 8, 10, 12, 20]), digits, "right")
        found.append((shape, span_hashes(lower_ascii(part), first, last), coarse.astype(np.uint8), bucket.astype(np.uint8)))
    return tuple(np.concatenate(column) for column in zip(*found))


@dataclass
class Crf:
    """Weights of a linear-chain CRF over ``LABELS``."""

    shapes: np.ndarray  # sorted hashes that training saw; 0 stands for any other
    words: np.ndarray
    tables: list[np.ndarray]  # one for each feature: values x labels
    moves: np.ndarray  # label before x label
    opening: np.ndarray

    @staticmethod
    def _known(vocabulary: np.ndarray, hashes: np.ndarray) -> np.ndarray:
        sieve = np.zeros(1 << 16, bool)
        sieve[vocabulary & np.uint64(0xFFFF)] = True
        out = np.zeros(len(hashes), np.int32)
        may = np.flatnonzero(sieve[hashes & np.uint64(0xFFFF)])
        at = np.minimum(np.searchsorted(vocabulary, hashes[may]), len(vocabulary) - 1)
        out[may] = np.where(vocabulary[at] == hashes[may], at + 1, 0)
        return out

    def values(self, looks, first_of_line: np.ndarray) -> list[np.ndarray]:
        """The value of each feature at each word; neighbours across a line's edge have value 0."""
        shape, word = self._known(self.shapes, looks[0]), self._known(self.words, looks[1])
        coarse, digits = looks[2].astype(np.int32), looks[3].astype(np.int32)
        last = np.append(first_of_line[1:], True)

        def left(x):
            return np.where(first_of_line, 0, np.roll(x, 1))

        def right(x):
            return np.where(last, 0, np.roll(x, -1))

        near = (left(coarse + 1) * (_COARSE + 1) + coarse + 1) * (_COARSE + 1) + right(coarse + 1)
        return [shape, word, near, coarse * 11 + digits, left(shape), right(shape), left(word), right(word), left(coarse * 11 + digits) * 11 + digits]

    def scores(self, looks, first_of_line: np.ndarray, chunk: int = 1 << 16) -> np.ndarray:
        """The emissions of all words, chunk by chunk; a chunk sees the word before and the one after it."""
        n = len(first_of_line)
        out = np.empty((n, len(LABELS)), np.float32)
        for lo in range(0, n, chunk):
            a, b = max(0, lo - 1), min(n, lo + chunk + 1)
            got = self.emissions(self.values([x[a:b] for x in looks], first_of_line[a:b]))
            out[lo : lo + chunk] = got[lo - a : lo - a + chunk]
        return out

    def emissions(self, values: list[np.ndarray]) -> np.ndarray:
        out = self.tables[0][values[0]]
        for weights, at in zip(self.tables[1:], values[1:]):
            out += weights[at]
        return out

    def decode(self, emissions: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        """The best labels of every line by Viterbi, all lines in step, longest first."""
        n, k = emissions.shape
        order = np.argsort(-lengths, kind="stable")
        starts, lengths = starts[order], lengths[order]
        back = np.zeros((n, k), np.uint8)
        active = np.searchsorted(-lengths, -np.arange(1, (lengths[0] if len(lengths) else 0) + 1), "right")
        best = self.opening + emissions[starts]
        finals = np.zeros((len(starts), k), np.float32)
        for t in range(1, len(active) + 1):
            on = active[t] if t < len(active) else 0
            finals[on : len(best)] = best[on:]
            if not on:
                break
            prior, at = best[:on], starts[:on] + t
            new = prior[:, :1] + self.moves[0]
            come = np.zeros((on, k), np.uint8)
            for j in range(1, k):
                other = prior[:, j : j + 1] + self.moves[j]
                come[other > new] = j
                np.maximum(new, other, out=new)
            back[at] = come
            best = new + emissions[at]
        labels = np.zeros(n, np.uint8)
        now = finals.argmax(axis=1).astype(np.uint8)
        for t in range(len(active) - 1, -1, -1):
            on = active[t]
            at = starts[:on] + t
            labels[at] = now[:on]
            now[:on] = back[at, now[:on]]
        return labels


def train(rows: list[tuple[str, list[str]]], rounds: int = 120, rate: float = 0.15, decay: float = 1e-4) -> Crf:
    """Maximum likelihood by full-batch adaptive gradient steps; forward and backward sums over all lines at once."""
    texts = [text.encode() for text, _ in rows]
    buf = np.frombuffer(b"\n".join(texts), np.uint8)
    offsets = np.cumsum([0, *(len(t) + 1 for t in texts)])
    offsets[-1] = len(buf)
    starts, ends, first = word_spans(buf, offsets)
    gold = np.array([LABELS.index(v) for _, labels in rows for v in labels])
    looks = _looks(buf, starts, ends)
    hashes, counts = np.unique(looks[1], return_counts=True)
    k = len(LABELS)
    crf = Crf(np.unique(looks[0]), hashes[counts > 2], [], np.zeros((k, k), np.float32), np.zeros(k, np.float32))
    opening = np.zeros(len(starts), bool)
    opening[first[:-1]] = True
    values = crf.values(looks, opening)
    sizes = [len(crf.shapes) + 1, len(crf.words) + 1, (_COARSE + 1) ** 3, _COARSE * 11, len(crf.shapes) + 1, len(crf.shapes) + 1, len(crf.words) + 1, len(crf.words) + 1, _COARSE * 121]
    crf.tables = [np.zeros((n, k), np.float32) for n in sizes]
    lengths = np.diff(first)
    longest = lengths.max()
    column = first[:-1, None] + np.arange(longest)
    there = np.arange(longest) < lengths[:, None]
    column = np.where(there, column, 0)
    one_hot = np.eye(k, dtype=np.float32)[gold]
    parameters = [*crf.tables, crf.moves, crf.opening]
    squares = [np.full_like(p, 1e-8) for p in parameters]
    inner = there[:, 1:]
    for _ in range(rounds):
        scores = crf.emissions(values)[column]
        forward = np.zeros_like(scores)
        backward = np.zeros_like(scores)
        forward[:, 0] = crf.opening + scores[:, 0]
        for t in range(1, longest):
            step = _logsum(forward[:, t - 1, :, None] + crf.moves, 1) + scores[:, t]
            forward[:, t] = np.where(there[:, t, None], step, forward[:, t - 1])
        for t in range(longest - 2, -1, -1):
            step = _logsum(crf.moves + (scores[:, t + 1] + backward[:, t + 1])[:, None, :], 2)
            backward[:, t] = np.where(there[:, t + 1, None], step, 0)
        total = _logsum(forward[:, -1], 1)
        marginal = np.exp(forward + backward - total[:, None, None])
        expected = np.zeros_like(one_hot)
        expected[column[there]] = marginal[there]
        pull = one_hot - expected
        pairs = np.exp(forward[:, :-1, :, None] + crf.moves + (scores + backward)[:, 1:, None, :] - total[:, None, None, None]) * inner[..., None, None]
        seen = np.zeros((k, k), np.float32)
        follows = ~opening[1:]
        np.add.at(seen, (gold[:-1][follows], gold[1:][follows]), 1)
        gradients = []
        for at, size in zip(values, sizes):
            g = np.zeros((size, k), np.float32)
            np.add.at(g, at, pull)
            gradients.append(g)
        gradients += [seen - pairs.sum(axis=(0, 1)), pull[opening].sum(axis=0)]
        for p, g, s in zip(parameters, gradients, squares):
            g = g / len(rows) - decay * p
            s += g * g
            p += rate * g / np.sqrt(s)
    return crf


def _logsum(x: np.ndarray, axis: int) -> np.ndarray:
    top = x.max(axis=axis, keepdims=True)
    return np.log(np.exp(x - top).sum(axis=axis)) + np.squeeze(top, axis)


# ---- finding

_EDGE = ".,;:!?\"'()[]{}<>*#$%&|"
_AT = re.compile(r"@|[\[(]at[\])]|\sat\s", re.I)


def _added_holds(kind: str, text: str) -> bool:
    """Whether a span that the CRF proposes is one of its kind."""
    digits = _NOT_DIGIT.sub("", text)
    if kind == "email":
        found = _AT.search(text)
        return bool(found) and found.start() > 0 and re.search(r"\.\w|dot", text[found.end() :], re.I) is not None
    if kind == "ip":
        return re.fullmatch(r"[0-9A-Fa-f:]{6,39}", text) is not None and text.count(":") >= 3 and len(digits) > 0
    if kind == "card":
        return 12 <= len(digits) <= 19 and luhn(digits)
    if kind == SECRET:
        return re.fullmatch(r"[A-Za-z0-9+/_=-]{16,}", text) is not None and 0 < len(digits) < len(text)
    return 7 <= len(digits) <= 15 and re.search(r"[A-Za-z]", text) is None


def _proposals(crf: Crf, buf: np.ndarray, offsets: np.ndarray) -> list[tuple[int, int, int, int]]:
    """(text, first byte, kind number, byte after the last) of every run of words of one kind."""
    starts, ends, first = word_spans(buf, offsets)
    if not len(starts):
        return []
    breaks = np.zeros(len(buf) + 1, np.int32)
    np.cumsum(buf == 10, out=breaks[1:])
    opening = np.zeros(len(starts), bool)
    opening[first[:-1][np.diff(first) > 0]] = True
    opening[1:] |= breaks[starts[1:]] > breaks[starts[:-1]]
    lines = np.flatnonzero(opening)
    lengths = np.diff(np.append(lines, len(starts)))
    labels = crf.decode(crf.scores(_looks(buf, starts, ends), opening), lines, lengths)
    if not labels.any():
        return []
    change = opening.copy()
    change[1:] |= labels[1:] != labels[:-1]
    runs = np.flatnonzero(change)
    stops = np.append(runs[1:], len(starts)) - 1
    some = labels[runs] > 0
    runs, stops = runs[some], stops[some]
    text = np.searchsorted(first, runs, "right") - 1
    return list(zip(text.tolist(), starts[runs].tolist(), (labels[runs].astype(int) - 1).tolist(), ends[stops].tolist()))


def _code_points(buf: np.ndarray, at: int, places: list[int]) -> dict[int, int]:
    """How many code points lie between byte ``at`` and each of the places, which rise."""
    out, count = {}, 0
    for place in places:
        count += int(np.count_nonzero((buf[at:place] & 0xC0) != 0x80))
        at, out[place] = place, count
    return out


def spans_of(crf: Crf, column: pa.Array) -> list[tuple[list, list]]:
    """For each text its base spans and all spans, as sorted (start, kind number, end) in code points."""
    out: list[tuple[list, list]] = []
    for lo, hi, buf, offsets in text_slices(column):
        flagged = np.zeros(len(buf) + 1, np.int64)
        np.cumsum(_DIGIT[buf] | (buf == 64), out=flagged[1:])
        proposed: dict[int, list] = {}
        for i, *span in _proposals(crf, buf, offsets):
            proposed.setdefault(i, []).append(span)
        has = np.diff(flagged[offsets]) > 0
        for i in range(hi - lo):
            if not has[i] and i not in proposed:
                out.append(([], []))
                continue
            raw = buf[offsets[i] : offsets[i + 1]].tobytes()
            text = raw.decode("utf-8", "replace")
            base = base_spans(text) if has[i] else []
            own = proposed.get(i, ())
            points = _code_points(buf, int(offsets[i]), sorted({x for start, _, end in own for x in (start, end)}))
            added = []
            for start, kind, end in own:
                start, end = points[start], points[end]
                shown = text[start:end]
                # outer punctuation is no part of the span; a bracket that opens a telephone number is
                end -= len(shown) - len(shown.rstrip(_EDGE))
                start += len(shown) - len(shown.lstrip(_EDGE if LABELS[kind + 1] != "phone" else _EDGE.replace("(", "")))
                if start < end and _added_holds(LABELS[kind + 1], text[start:end]) and all(e <= start or end <= s for s, _, e in base):
                    added.append((start, kind, end))
            out.append((base, sorted(base + added)))
    return out


def find(docs: DataFrame, crf: Crf | None = None) -> DataFrame:
    """``docs`` with base and spans: arrays of (kind, start, end), code points, sorted by start and kind."""
    docs = without(docs, "base", "spans")
    if crf is None:
        rows = labelled_table(docs.sparkSession, contexts=context_words(docs)).collect()  # 1,000 lines
        crf = train([(r[0], r[1]) for r in rows])
    shared = docs.sparkSession.sparkContext.broadcast(crf)
    span = pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())])
    at = [c.lower() for c in docs.columns].index("text")

    def found(batches):
        for batch in batches:
            pairs = spans_of(shared.value, batch.column(at))
            named = [pa.array([[{"kind": LABELS[k + 1], "start": s, "end": e} for s, k, e in pair[i]] for pair in pairs], pa.list_(span)) for i in (0, 1)]
            yield pa.RecordBatch.from_arrays([*batch.columns, *named], names=[*batch.schema.names, "base", "spans"])

    kind = "array<struct<kind:string,start:long,end:long>>"
    return docs.mapInArrow(found, f"{docs.schema.toDDL()}, base {kind}, spans {kind}")


def query(spark, sf_dir):
    """Contract digest: counts and hash of the base spans, all spans written out, and how many secrets and spans there are."""
    found = find(table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("doc_id"), "text"))

    def written(column):
        return F.array_join(F.transform(column, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")

    def count(column, kind):
        return F.size(F.filter(column, lambda s: s["kind"] == kind)).cast("long")

    counts = [count("base", kind).alias(f"n_{kind}") for kind in KINDS]
    more = [count("spans", SECRET).alias("n_secret"), F.size("spans").cast("long").alias("n_spans")]
    return found.select("doc_id", *counts, F.sha2(written("base"), 256).alias("base_sha256"), written("spans").alias("spans"), *more)
