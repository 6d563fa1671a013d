"""Personal data: exact base rules, and a character-level bidirectional LSTM with CRF transitions that adds spans.

The network is trained in numpy on labelled spans: those of the base rules in windows of sampled texts, and values in
many forms that the rules miss (mail addresses spelt out, telephone numbers without plus, cards with odd separators or
side by side, addresses in brackets or of version 6), written into windows of sampled texts. It reads every character of
every whole text in overlapping windows. Windows are decoded by Viterbi, and the spans of all windows of a text are
reconciled: those of one kind that overlap are joined, what overlaps a base span is left out, so base spans always stay
as they are, and what is left must pass its kind's own check (check digit, parts up to 255, number of digits, an address
once spelt-out signs are read).

Most characters hold nothing. Where the best path cannot have a tag is proved by a bound on every stretch of tags that
holds the place, which costs two steps a character; only what is left open is decoded in full, with the same result.

Defined results: a null or empty text has no spans; rows are judged one by one, so repeated rows and null ids need no
care; a table without rows trains on invented text alone; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

KINDS = ("email", "ip", "card", "phone")
#: Characters of a window, and how far the next one begins.
SIZE, STEP = 448, 400
#: Windows that are decoded together.
TOGETHER = 1024
#: Bounds of training: sampled texts, windows taken from each, values written into such windows; characters of a window.
SAMPLE_TEXTS, TEXT_WINDOWS, INVENTED, LEARNT = 400, 3, 2400, 80
TAGS = 1 + 2 * len(KINDS)  # none, then begin and inside of each kind

#: The base patterns, in forms that scan in linear time and match alike.
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL_CHARS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")
_MAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_SPELT = ((re.compile(r"\s*[\[({<]?\s*\b(?:at|AT)\b\s*[\])}>]?\s*|\s*@\s*"), "@"), (re.compile(r"\s*[\[({<]?\s*\b(?:dot|DOT)\b\s*[\])}>]?\s*"), "."))


def luhn(digits: str) -> bool:
    total = 0
    for k, d in enumerate(reversed(digits)):
        v = int(d) * (1 + k % 2)
        total += v - 9 * (v > 9)
    return total % 10 == 0


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind index, end) of the base rules' matches, by start, then kind."""
    found, done = [], 0
    at = text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL_CHARS:
            start -= 1
        if start < at and (m := _DOMAIN.match(text, at + 1)):
            found.append((start, 0, m.end()))
            done = m.end()
        at = text.find("@", max(done, at + 1))
    if _DIGIT.search(text):
        found += [(m.start(), 1, m.end()) for m in _IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m[0].split("."))]
        for m in _CARD.finditer(text):
            digits = m[0].replace(" ", "").replace("-", "")
            if 12 <= len(digits) <= 19 and luhn(digits):
                found.append((m.start(), 2, m.end()))
        found += [(m.start(), 3, m.end()) for m in _PHONE.finditer(text) if 9 <= sum(c.isdigit() for c in m[0]) <= 15]
    return sorted(found)


_SYMBOL = np.minimum(np.arange(0x3000), 128).astype(np.uint8)
_SYMBOL[0x2000:] = 129


def symbols(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(symbols of all texts in a row, offsets): ASCII by itself (its NUL as 127), one for other letters, one for the rest."""
    points = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)
    found = _SYMBOL[np.minimum(points, len(_SYMBOL) - 1)]
    found[found == 0] = 127
    return found, np.concatenate([[0], np.cumsum([len(t) for t in texts])]).astype(np.int64)


def codes(windows: list[str], size: int = SIZE) -> np.ndarray:
    """(windows, size) symbols; 0 past the end."""
    flat, offsets = symbols(windows)
    at = offsets[:-1, None] + np.arange(size)
    return np.where(at < offsets[1:, None], flat[np.minimum(at, max(0, len(flat) - 1))] if len(flat) else 0, 0).astype(np.uint8)


class Tagger:
    """Embedding, LSTMs in both directions, emissions and CRF transitions, in float32.

    What a cell forgets is what it does not take in (coupled gates), and all squashing is by clipped straight lines.
    """

    def __init__(self, embed: int = 8, hidden: int = 8, seed: int = 3):
        rng = np.random.default_rng(seed)
        draw = lambda *shape: (rng.normal(0, 1 / np.sqrt(shape[0]), shape)).astype(np.float32)
        self.hidden = hidden
        self.p = {"E": draw(130, embed) * 2, "O": draw(2 * hidden, TAGS), "ob": np.zeros(TAGS, np.float32), "A": np.zeros((TAGS, TAGS), np.float32)}
        gate = np.r_[np.full(2 * hidden, 0.25), np.ones(hidden)].astype(np.float32)
        for d in "fb":
            self.p |= {f"W{d}": draw(embed, 3 * hidden) * gate, f"U{d}": draw(hidden, 3 * hidden) * gate, f"c{d}": np.zeros(3 * hidden, np.float32)}
            self.p[f"c{d}"][:hidden] = 0.3
            self.p[f"c{d}"][hidden : 2 * hidden] = 0.5

    def _direction(self, x: np.ndarray, d: str, e: np.ndarray, trace: list | None = None) -> None:
        """Adds one direction's share to the emissions e (steps, tags, windows); x: (steps, windows).

        Gates are rows and windows columns, so that every operation runs over contiguous numbers.
        """
        steps, n = x.shape
        k, x = self.hidden, x.astype(np.intp)
        # A symbol's input to the gates does not depend on its place.
        table = np.ascontiguousarray((self.p["E"] @ self.p[f"W{d}"] + self.p[f"c{d}"]).T)
        u, out = np.ascontiguousarray(self.p[f"U{d}"].T), np.ascontiguousarray((self.p["O"][:k] if d == "f" else self.p["O"][k:]).T)
        h, c = np.zeros((k, n), np.float32), np.zeros((k, n), np.float32)
        z, fed, tc, tmp, add = (np.empty((rows, n), np.float32) for rows in (3 * k, 3 * k, k, k, TAGS))
        for t in range(steps) if d == "f" else range(steps - 1, -1, -1):
            if trace is not None:
                z, tc, last_c, last_h = np.empty_like(z), np.empty_like(tc), c, h
                c, h = c.copy(), np.empty_like(h)
            np.dot(u, h if trace is None else last_h, out=fed)
            np.take(table, x[t], axis=1, out=z, mode="clip")  # unlike "raise", writes in place
            z += fed
            i, o, g = z[:k], z[k : 2 * k], z[2 * k :]
            np.clip(z[: 2 * k], 0, 1, out=z[: 2 * k])
            np.clip(g, -1, 1, out=g)
            # The cell moves from what it held to what is new, as far as its gate is open; so it stays within [-1, 1].
            np.subtract(g, c, out=tmp)
            tmp *= i
            c += tmp
            np.multiply(o, c, out=h)
            np.dot(out, h, out=add)
            e[t] += add
            if trace is not None:
                trace.append((t, z, last_c, last_h, h, c))

    def emissions(self, x: np.ndarray, traces: tuple[list, list] | None = None) -> np.ndarray:
        """(steps, tags, windows) of x (steps, windows)."""
        e = np.empty((x.shape[0], TAGS, x.shape[1]), np.float32)
        e[:] = self.p["ob"][:, None]
        for i, d in enumerate("fb"):
            self._direction(x, d, e, traces[i] if traces else None)
        return e

    def open_places(self, e: np.ndarray) -> np.ndarray:
        """(steps, windows): where the best path may have a tag; elsewhere every stretch of tags loses more than it gains.

        A stretch is bounded from either side: each tag goes on by its own transition, or from the best of all others by
        the best transition into it.
        """
        a = self.p["A"] - self.p["A"][0, 0]
        inner = a[1:, 1:].copy()
        same = inner.diagonal().copy()[:, None]
        np.fill_diagonal(inner, -np.inf)
        into, out_of = inner.max(axis=0)[:, None], inner.max(axis=1)[:, None]
        enter, leave = np.maximum(a[0, 1:], 0)[:, None], np.maximum(a[1:, 0], 0)[:, None]
        enter0, leave0 = a[0, 1:, None], a[1:, 0, None]
        steps, _, n = e.shape
        # First only the best that any stretch has come to, without keeping it: most windows never get that far.
        best, other, gain = (np.full((TAGS - 1, n), -np.inf, np.float32) for _ in range(3))
        top, most = (np.full(n, -np.inf, np.float32) for _ in range(2))
        for t in range(steps):
            np.add(into, most, out=other)
            best += same
            np.maximum(best, other, out=best)
            # At a window's ends a stretch need not be entered or left.
            np.maximum(best, enter0 if t else enter, out=best)
            np.subtract(e[t, 1:], e[t, 0], out=gain)
            best += gain
            np.max(best, axis=0, out=most)
            np.maximum(top, most, out=top)
        out = np.zeros((steps, n), bool)
        some = np.flatnonzero(top + leave.max() > -1e-3)
        if not len(some):
            return out
        gain = e[:, 1:, some] - e[:, :1, some]
        ahead = np.empty_like(gain)
        ahead[0] = gain[0] + enter
        for t in range(1, steps):
            now = np.maximum(ahead[t - 1] + same, enter0)
            np.maximum(now, ahead[t - 1].max(axis=0) + into, out=now)
            np.add(now, gain[t], out=ahead[t])
        behind = gain[-1] + leave
        out[-1, some] = (ahead[-1] + leave > -1e-3).any(axis=0)
        for t in range(steps - 2, -1, -1):
            now = np.maximum(behind + same, leave0)
            np.maximum(now, behind.max(axis=0) + out_of, out=now)
            behind = now + gain[t]
            out[t, some] = (ahead[t] + now > -1e-3).any(axis=0)
        return out

    def viterbi(self, e: np.ndarray) -> np.ndarray:
        """The best tag of each character, (windows, steps), of emissions (steps, tags, windows)."""
        steps, _, n = e.shape
        a_ = self.p["A"]
        score, back = e[0], np.empty((steps, TAGS, n), np.int8)
        for t in range(1, steps):
            best, place = score[0] + a_[0][:, None], back[t]
            place[:] = 0
            for i in range(1, TAGS):
                way = score[i] + a_[i][:, None]
                np.copyto(place, i, where=way > best)
                np.maximum(best, way, out=best)
            score = best + e[t]
        tags = np.empty((n, steps), np.int8)
        tags[:, -1] = score.argmax(axis=0)
        for t in range(steps - 1, 0, -1):
            tags[:, t - 1] = back[t][tags[:, t], np.arange(n)]
        return tags

    def decode(self, x: np.ndarray) -> Iterator[tuple[int, int, np.ndarray]]:
        """(row of x, first place, tags from there) of the stretches that hold all tags but none."""
        e = self.emissions(np.ascontiguousarray(x.T))
        if (past := x.T == 0).any():
            np.copyto(e[:, 1:], -1e4, where=past[:, None])
        # Closed places have no tag, so runs of open ones are decoded each by itself, between closed neighbours.
        n, steps = x.shape
        flat = np.zeros((n, steps + 2), np.int8)
        flat[:, 1:-1] = self.open_places(e).T
        edge = np.flatnonzero(np.diff(flat.ravel(), append=np.int8(0)))
        row, first = np.divmod(edge[::2], steps + 2)
        length = edge[1::2] - edge[::2]
        order = np.argsort(length, kind="stable")
        for at in range(0, len(order), 1024):
            own = order[at : at + 1024]
            # One closed place before and behind, where the window has it.
            begin = np.maximum(first[own] - 1, 0)
            stop = np.minimum(first[own] + length[own] + 1, steps)
            place = begin + np.arange(int((stop - begin).max()))[:, None]
            shut = (place < first[own]) | (place >= first[own] + length[own])
            part = np.ascontiguousarray(e[np.minimum(place, steps - 1), :, row[own]].transpose(0, 2, 1))
            np.copyto(part[:, 1:], -1e4, where=shut[:, None])
            tags = self.viterbi(part)
            for i in np.flatnonzero(tags.any(axis=1)).tolist():
                yield int(row[own[i]]), int(begin[i]), tags[i]

    def gradients(self, x: np.ndarray, y: np.ndarray) -> dict[str, np.ndarray]:
        """Of the negative log-likelihood of tags y, by forward-backward sums and backpropagation through time."""
        traces: tuple[list, list] = ([], [])
        e = self.emissions(np.ascontiguousarray(x.T), traces)
        steps, _, n = e.shape
        a_ = self.p["A"]
        ea = np.exp(a_ - a_.max())
        alpha, beta = np.empty_like(e), np.zeros_like(e)
        alpha[0] = e[0]
        for t in range(1, steps):
            top = alpha[t - 1].max(axis=0)
            alpha[t] = np.log(ea.T @ np.exp(alpha[t - 1] - top) + 1e-30) + (top + a_.max()) + e[t]
        for t in range(steps - 2, -1, -1):
            after = e[t + 1] + beta[t + 1]
            top = after.max(axis=0)
            beta[t] = np.log(ea @ np.exp(after - top) + 1e-30) + (top + a_.max())
        top = alpha[-1].max(axis=0)
        z = np.log(np.exp(alpha[-1] - top).sum(axis=0)) + top
        de = np.exp(alpha + beta - z)
        # Sums over all places of the chances of each pair of tags.
        left, right = np.exp(alpha[:-1] - alpha[:-1].max(axis=1, keepdims=True)), (e + beta)[1:]
        right = np.exp(right - right.max(axis=1, keepdims=True))
        whole = (np.matmul(ea.T, left) * right).sum(axis=1, keepdims=True)
        da = np.tensordot(left / whole, right, ([0, 2], [0, 2])) * ea
        tags = y.T
        np.add.at(da, (tags[:-1].ravel(), tags[1:].ravel()), -1)
        de[np.arange(steps)[:, None], tags, np.arange(n)[None, :]] -= 1
        de /= n
        k = self.hidden
        g = {"A": da.astype(np.float32) / n, "ob": de.sum(axis=(0, 2)), "E": np.zeros_like(self.p["E"]), "O": np.zeros_like(self.p["O"])}
        for d, trace, own in (("f", traces[0], slice(0, k)), ("b", traces[1], slice(k, 2 * k))):
            part = np.matmul(self.p["O"][own], de)
            dz_all = np.empty((steps, 3 * k, n), np.float32)
            du, do, u = np.zeros_like(self.p[f"U{d}"]), np.zeros((k, TAGS), np.float32), self.p[f"U{d}"]
            dh, dc = np.zeros((k, n), np.float32), np.zeros((k, n), np.float32)
            for t, zs, last_c, last_h, h, c in reversed(trace):
                do += h @ de[t].T
                i, o, gg = zs[:k], zs[k : 2 * k], zs[2 * k :]
                dh += part[t]
                dc += dh * o
                dz = dz_all[t]
                np.multiply(dc, gg - last_c, out=dz[:k])
                np.multiply(dh, c, out=dz[k : 2 * k])
                np.multiply(dc, i, out=dz[2 * k :])
                gates = zs[: 2 * k]
                dz[: 2 * k] *= (gates > 0) & (gates < 1)
                dz[2 * k :] *= np.abs(gg) < 1
                du += last_h @ dz.T
                dh, dc = u @ dz, dc * (1 - i)
            g["O"][own] += do
            flat, sym = dz_all.transpose(1, 0, 2).reshape(3 * k, -1), x.T.ravel()
            table = np.stack([np.bincount(sym, row, minlength=130) for row in flat], axis=1).astype(np.float32)
            g |= {f"U{d}": du, f"W{d}": self.p["E"].T @ table, f"c{d}": table.sum(axis=0)}
            g["E"] += table @ self.p[f"W{d}"].T
        return g

    def fit(self, x: np.ndarray, y: np.ndarray, epochs: int = 12, batch: int = 64, rate: float = 0.02, seed: int = 5) -> Tagger:
        rng = np.random.default_rng(seed)
        first, second = ({k: np.zeros_like(v) for k, v in self.p.items()} for _ in range(2))
        step = 0
        total = epochs * (len(x) // batch + 1)
        for _ in range(epochs):
            order = rng.permutation(len(x))
            for at in range(0, len(order), batch):
                own = order[at : at + batch]
                step += 1
                lr = rate * (1 - step / (total + 1))
                found = self.gradients(x[own], y[own])
                norm = np.sqrt(sum(float((v * v).sum()) for v in found.values()))
                for k, v in found.items():
                    v = v * min(1.0, 5.0 / (norm + 1e-9))
                    first[k] = 0.9 * first[k] + 0.1 * v
                    second[k] = 0.99 * second[k] + 0.01 * v * v
                    self.p[k] = (self.p[k] - lr * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.99**step)) + 1e-6)).astype(np.float32)
        return self


# ---- labelled spans --------------------------------------------------------------------------------------------------


def labelled(spans: list[tuple[int, int, int]], size: int = LEARNT) -> np.ndarray:
    """Tags of a window's characters."""
    tags = np.zeros(size, np.int8)
    # A card inside a telephone number or the like: the longer span names the characters.
    for a, kind, b in sorted(spans, key=lambda s: s[2] - s[0]):
        if a < size:
            tags[a:b] = 2 + 2 * kind
            tags[a] = 1 + 2 * kind
    return tags


def _word(rng: np.random.Generator, least: int = 2, most: int = 9) -> str:
    return "".join(rng.choice(list("abcdefghiklmnoprstuvwy"), rng.integers(least, most)))


def _digits(rng: np.random.Generator, n: int) -> str:
    return "".join(map(str, rng.integers(0, 10, n)))


def _card(rng: np.random.Generator) -> str:
    body = str(rng.integers(3, 7)) + _digits(rng, int(rng.choice([11, 13, 14, 14, 14, 14, 17])))
    return next(body + str(d) for d in range(10) if luhn(body + str(d)))


def _grouped(text: str, sep: str) -> str:
    return sep.join(text[i : i + 4] for i in range(0, len(text), 4))


def _local(rng: np.random.Generator) -> str:
    return str(rng.choice([_word(rng, 3, 9), f"{_word(rng)}.{_word(rng)}", f"{_word(rng)}_{_word(rng)}", f"{_word(rng)}{_digits(rng, 2)}", f"{_digits(rng, 2)}"]))


def _host(rng: np.random.Generator, dot: str) -> str:
    names = [_word(rng, 3, 9) + (_digits(rng, 1) if rng.random() < 0.3 else ""), str(rng.choice(["com", "org", "net", "de", "fr", "es"]))]
    return dot.join(([_word(rng, 3, 7)] if rng.random() < 0.4 else []) + names)


def _octets(rng: np.random.Generator, dot: str) -> str:
    return dot.join(str(rng.integers(0, 256)) for _ in range(4))


def _phone(rng: np.random.Generator, form: str) -> str:
    return "".join(_digits(rng, 1) if c == "9" else c for c in form)


def _spelt(rng: np.random.Generator, at: str, dot: str) -> str:
    return _local(rng) + at + _host(rng, dot)


#: Forms that the base rules miss, as (name, kind, maker). How people write such things.
FORMS: list = [
    *[(f"mail {at!r} {dot!r}", 0, lambda r, at=at, dot=dot: _spelt(r, at, dot)) for at, dot in ((" @ ", "."), (" at ", " dot "), (" [at] ", " [dot] "), ("(at)", "."), ("[at]", "."), (" AT ", " DOT "), (" (at) ", " (dot) "), ("@ ", "."), (" @", "."))],
    *[(f"ip {dot!r}", 1, lambda r, dot=dot: _octets(r, dot)) for dot in (" . ", "[.]", "(.)", " dot ")],
    ("ip 6", 1, lambda r: ":".join(f"{r.integers(1, 65536):x}" for _ in range(8))),
    ("ip 6 short", 1, lambda r: "fe80::" + ":".join(f"{r.integers(1, 65536):x}" for _ in range(4))),
    *[(f"card {sep!r}", 2, lambda r, sep=sep: _grouped(_card(r), sep)) for sep in (".", "_", "  ", " - ", "/")],
    ("two cards", 2, lambda r: (_card(r), " ", _card(r))),
    ("card after number", 2, lambda r: (None, _digits(r, int(r.integers(1, 4))) + " ", _card(r))),
    *[(f"phone {form}", 3, lambda r, form=form: _phone(r, form)) for form in ("(999) 999-9999", "999-999-9999", "999.999.9999", "0999 999 9999", "00999 999 99999", "0999/9999999", "1-999-999-9999", "99 99 99 99 99")],
]
#: Forms that are never trained on, to measure what is learnt beyond the forms seen.
UNSEEN: list = [
    ("mail '{at}' '.'", 0, lambda r: _spelt(r, "{at}", ".")),
    ("mail ' at ' '.'", 0, lambda r: _spelt(r, " at ", ".")),
    ("ip ' .'", 1, lambda r: _octets(r, " .")),
    ("card '-' doubled", 2, lambda r: _grouped(_card(r), "--")),
    ("phone (0999) 999999", 3, lambda r: _phone(r, "(0999) 999999")),
    ("phone 999 999 9999", 3, lambda r: _phone(r, "999 999 9999")),
]
#: What is no personal data though it looks a little like it.
OTHERS: list = [
    lambda r: f"{_digits(r, 2)}.{_digits(r, 2)}", lambda r: _digits(r, int(r.integers(1, 7))), lambda r: _digits(r, 2) + "%", lambda r: f"{_digits(r, 1)}.{_digits(r, 1)}.{_digits(r, 1)}", lambda r: "@" + _word(r),
    lambda r: f"20{_digits(r, 2)}-0{r.integers(1, 10)}-{r.integers(10, 31)}", lambda r: f"{r.integers(10, 24)}:{r.integers(10, 60)}:{r.integers(10, 60)}", lambda r: f"{_word(r)} at {_word(r)}", lambda r: f"${_digits(r, 3)}.{_digits(r, 2)}",
    lambda r: "".join(r.choice(list("0123456789abcdef"), 32)), lambda r: f"{_digits(r, 4)} {_digits(r, 3)}", lambda r: f"No. {_digits(r, 5)}", lambda r: f"({_digits(r, 1)})", lambda r: f"{_digits(r, 4)}-{_digits(r, 4)}", lambda r: f"dot {_word(r)}",
]


def invented(rng: np.random.Generator, carriers: list[str], n: int = INVENTED, forms: list = FORMS, size: int = LEARNT) -> list[tuple[str, list[tuple[int, int, int]]]]:
    """Windows of carrier texts, or of random words, with a value of one of the forms, or of none, and all their spans."""
    out = []
    for _ in range(n):
        # A quarter of the cases hold no value of a form.
        if rng.random() < 0.25:
            kind, parts = -1, [OTHERS[rng.integers(len(OTHERS))](rng)]
        else:
            _, kind, make = forms[rng.integers(len(forms))]
            parts = make(rng)
            parts = [parts] if isinstance(parts, str) else list(parts)
        own = carriers[rng.integers(len(carriers))] if carriers and rng.random() < 0.8 else " ".join(_word(rng) for _ in range(20))
        gaps = [i for i, c in enumerate(own) if c in " \n"] or [0]
        cut = gaps[rng.integers(len(gaps))]
        left, right = own[:cut], own[cut + 1 :]
        value = "".join(p for p in parts if p)
        left = left[-int(rng.integers(0, max(1, size - len(value)))) or len(left) :] if left else ""
        text = f"{left} " if left else ""
        spans, at = [], len(text)
        for i, p in enumerate(parts):
            if p:
                if kind >= 0 and i % 2 == 0:
                    spans.append((at, kind, at + len(p)))
                at += len(p)
        text += value + str(rng.choice([" ", " ", " ", ". ", ", ", "\n"])) + right
        spans += [s for s in base_spans(text) if not any(s[0] < b and a < s[2] for a, _, b in spans)]
        out.append((text[:size], [(a, k, min(b, size)) for a, k, b in spans if a < size]))
    return out


def sampled_windows(docs: DataFrame, text_col: str = "text", texts: int = SAMPLE_TEXTS, each: int = TEXT_WINDOWS, size: int = LEARNT) -> list[str]:
    """At most `each` windows of `size` characters of each of at most `texts` different texts, the same on every run.

    Half the texts have a digit or @. Windows begin near a base span where there is one; only they reach the driver.
    """
    text = F.col(text_col).cast("string")
    rows = docs.select(text.alias("t")).where("t is not null and t <> ''").select("t", F.xxhash64("t").alias("h"))
    chosen = None
    for marked in (True, False):
        some = rows.where(F.col("t").rlike("[0-9@]") == marked).select("h").distinct().orderBy("h").limit(texts // 2)
        chosen = some if chosen is None else chosen.unionByName(some)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hashes, found = [], []
            for t, h in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                rng = np.random.default_rng(abs(h))
                spans = base_spans(t)
                for _ in range(each):
                    if spans and rng.random() < 0.7:
                        at = max(0, spans[rng.integers(len(spans))][0] - int(rng.integers(0, size - 30)))
                    else:
                        at = int(rng.integers(0, max(1, len(t) - size)))
                    found.append(t[at : at + size])
                    hashes.append(h)
            yield pa.RecordBatch.from_arrays([pa.array(hashes, pa.int64()), pa.array(found, pa.string())], ["h", "w"])

    # Hashes first: at most `texts` of them are sent out.
    own = rows.join(F.broadcast(chosen.withColumnRenamed("h", "c")), F.col("h") == F.col("c")).select("t", "h")
    # Copies of a text yield the same windows.
    return sorted(r["w"] for r in own.mapInArrow(cut, "h long, w string").distinct().limit(texts * each).collect())


def fit(docs: DataFrame, text_col: str = "text", texts: int = SAMPLE_TEXTS, values: int = INVENTED) -> Tagger:
    """Trains on the base rules' spans in sampled windows, and on `values` values written into such windows."""
    windows = sampled_windows(docs, text_col, texts)
    rng = np.random.default_rng(11)
    cases = [(w, base_spans(w)) for w in windows] + invented(rng, windows, values)
    return Tagger().fit(codes([t for t, _ in cases], LEARNT), np.stack([labelled(s) for _, s in cases]))


# ---- whole texts -----------------------------------------------------------------------------------------------------


def passes(kind: int, part: str) -> bool:
    """Whether characters tagged as one kind can be that: the kind's own exact check."""
    if kind == 0:
        for pattern, sign in _SPELT:
            part = pattern.sub(sign, part)
        return bool(_MAIL.fullmatch(part))
    if kind == 1:
        if ":" in part:
            groups = part.split(":")
            return 4 <= len(groups) <= 8 and all(re.fullmatch("[0-9A-Fa-f]{0,4}", x) for x in groups) and (len(groups) == 8 or "::" in part)
        groups = re.findall("[0-9]+", part)
        return len(groups) == 4 and all(len(x) <= 3 and int(x) <= 255 for x in groups)
    digits = re.sub("[^0-9]", "", part)
    return 12 <= len(digits) <= 19 and luhn(digits) if kind == 2 else 9 <= len(digits) <= 15


def reconciled(found: list[tuple[int, int, int]], base: list[tuple[int, int, int]], text: str) -> list[tuple[int, int, int]]:
    """Added spans: the windows' spans of one kind joined where they overlap, whole words of them that touch no base span."""
    joined: list[list[int]] = []
    for kind in range(len(KINDS)):
        at = len(joined)
        for a, k, b in sorted(s for s in found if s[1] == kind):
            if len(joined) > at and a < joined[-1][2]:
                joined[-1][2] = max(joined[-1][2], b)
            else:
                joined.append([a, k, b])
    out = []
    for a, k, b in joined:
        while a < b and text[a] in " \n\t.,;:":
            a += 1
        while b > a and text[b - 1] in " \n\t.,;:":
            b -= 1
        whole = not (a and text[a - 1].isalnum() and text[a].isalnum()) and not (b < len(text) and text[b].isalnum() and text[b - 1].isalnum())
        if a < b and whole and passes(k, text[a:b]) and not any(a < e and s < b for s, _, e in base):
            out.append((a, k, b))
    return out


def windows_of(offsets: np.ndarray, size: int = SIZE, step: int = STEP) -> tuple[np.ndarray, np.ndarray]:
    """(text, start within all texts) of windows that cover every character, each overlapping the next by size - step."""
    length = np.diff(offsets)
    many = np.where(length > 0, np.maximum(0, -(-(length - size) // step)) + 1, 0)
    text = np.repeat(np.arange(len(length)), many)
    nth = np.arange(len(text)) - np.repeat(np.cumsum(many) - many, many)
    return text, offsets[text] + nth * step


def tagged(tagger: Tagger, texts: list[str], spans: list[list[tuple[int, int, int]]]) -> list[list[tuple[int, int, int]]]:
    """The added spans of each text."""
    flat, offsets = symbols(texts)
    text, start = windows_of(offsets)
    found: list[list[tuple[int, int, int]]] = [[] for _ in texts]
    # Windows of like lengths go together, so that short texts cost little.
    length = np.minimum(SIZE, offsets[text + 1] - start)
    order = np.argsort(-(length // 16), kind="stable")
    padded = np.concatenate([flat, np.zeros(SIZE, np.uint8)])
    for at in range(0, len(order), TOGETHER):
        own = order[at : at + TOGETHER]
        size = int(length[own].max())
        x = padded[start[own, None] + np.arange(size)]
        x[np.arange(size) >= length[own, None]] = 0
        for w, skip, row in tagger.decode(x):
            i = int(text[own[w]])
            begin = int(start[own[w]] - offsets[i]) + skip
            kind = (row + 1) // 2
            edge = np.flatnonzero(np.concatenate([[True], (kind[1:] != kind[:-1]) | ((row[1:] % 2 == 1) & (row[1:] > 0)), [True]]))
            for a, b in zip(edge.tolist(), edge[1:].tolist()):
                if row[a]:
                    found[i].append((begin + a, int(kind[a]) - 1, min(begin + b, len(texts[i]))))
    return [reconciled(f, b, t) if f else [] for f, b, t in zip(found, spans, texts)]


def measured(tagger: Tagger, cases: list[tuple[str, list[tuple[int, int, int]]]]) -> tuple[float, float]:
    """(precision, recall) of added spans, exact to the character, on texts with known spans."""
    base = [base_spans(t) for t, _ in cases]
    got = tagged(tagger, [t for t, _ in cases], base)
    want = [[s for s in spans if s not in b] for (_, spans), b in zip(cases, base)]
    right = sum(len(set(g) & set(w)) for g, w in zip(got, want))
    return right / max(1, sum(map(len, got))), right / max(1, sum(map(len, want)))


def _shown(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in sorted(spans))


def scan(docs: DataFrame, tagger: Tagger, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_added), one for each row of docs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            row = 0
            while row < batch.num_rows:
                # About as many characters at a time, whole texts always.
                texts, total = [], 0
                while row + len(texts) < batch.num_rows and total < 4 * TOGETHER * STEP:
                    texts.append(batch.column(1)[row + len(texts)].as_py() or "")
                    total += len(texts[-1])
                part = batch.slice(row, len(texts))
                row += len(texts)
                different = list(dict.fromkeys(texts))
                base_of = {t: base_spans(t) for t in different}
                added_of = dict(zip(different, tagged(tagger, different, list(base_of.values()))))
                base, added = [base_of[t] for t in texts], [added_of[t] for t in texts]
                counts = [pa.array([sum(k == kind for _, k, _ in b) for b in base], pa.int64()) for kind in range(len(KINDS))]
                sha = pa.array([hashlib.sha256(_shown(b).encode()).hexdigest() for b in base])
                yield pa.RecordBatch.from_arrays([part.column(0), *counts, sha, pa.array([_shown(b + a) for b, a in zip(base, added)]), pa.array([len(a) for a in added], pa.int64())], ["doc_id", *(f"n_{k}" for k in KINDS), "base_sha256", "spans", "n_added"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col), F.col(text_col).cast("string")).mapInArrow(run, f"doc_id {kind}, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long")
