"""Personal data by fixed patterns and a character-level bidirectional LSTM with CRF transitions.

The tagger is trained in numpy from labelled spans that a seeded generator writes; training depends on
nothing but the parameters in this file. Whole texts are cut into overlapping windows on a fixed grid, and
each position's emission is the mean over its windows, weighted towards a window's middle. Viterbi decodes
across windows, in every stretch where an entity could pay: characters add at most their best entity score
over the outside tag's, and an entity's sum must make up for the transitions into and out of it; where no
run of characters does that, the best path is outside throughout and needs no decoding.
Every kind's definition asks for a digit or an at sign, plain or spelt out in brackets, so settled() takes no
span without one of _SIGNS: windows more than REACH characters from any are given to the outside tag without
computing their emissions. No accepted span is lost by it (tested against computing all of them).
A text over PIECE characters is tagged piece by piece, and a stretch over BLOCK decoded block by block,
each with OVERLAP characters more, which is longer than any entity; a span belongs to the piece and the
block that it begins in. So memory doesn't grow with a text.

The tagger finds what the patterns lose: a card beside other digits, an address with its dots in brackets,
an e-mail with its signs spelt out, a telephone number without a plus. A span is added if its text, with
such signs put back, is of its kind by the kind's own definition (settled()), and shares no character with a
base span or an earlier added one; base spans stay as they are. A failed base match is no base span.

Defined results: null text is empty; offsets are code points, ends exclusive; repeated rows repeat their
results; an empty table gives no rows; other columns pass through redact() unchanged.
"""

from __future__ import annotations

import bisect
import functools
import random
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from deltamp.llm.common import as_texts

KINDS = ("email", "ip", "card", "phone")
WIDTH, STEP, HIDDEN, EMBED = 128, 96, 12, 10
STEPS, BATCH, SEED, RATE, TRAIN_WIDTH = 420, 48, 7, 0.03, 64
PAD, PIECE, BLOCK, OVERLAP, REACH = 8, 500_000, 384, 128, 96
TAGS = 1 + 2 * len(KINDS)

# The contract's patterns. The e-mail pattern is run from its at signs, to stay linear.
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-"
_IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_TRIGGER = re.compile(r"[0-9@]")
_SIGNS = np.isin(np.arange(130), [ord(c) for c in "0123456789@[("])


def luhn(digits: str) -> bool:
    total = 0
    for k, d in enumerate(reversed(digits)):
        x = int(d) * (1 + k % 2)
        total += x - 9 * (x > 9)
    return total % 10 == 0


def _digits(text: str) -> str:
    return "".join(c for c in text if "0" <= c <= "9")


def holds(kind: str, text: str) -> bool:
    """Whether a whole string is of the kind, by the contract's pattern and its limits."""
    if kind == "email":
        local, at, domain = text.partition("@")
        return bool(at and local) and not local.strip(_LOCAL) and _DOMAIN.fullmatch(domain) is not None
    if kind == "ip":
        return re.fullmatch(r"[0-9]+(\.[0-9]+){3}", text) is not None and all(len(p) <= 3 and int(p or 0) <= 255 for p in (q.lstrip("0") for q in text.split(".")))
    d = _digits(text)
    if kind == "card":
        return _CARD.fullmatch(text) is not None and 13 <= len(d) <= 19 and luhn(d)
    return _PHONE.fullmatch(text) is not None and 9 <= len(d) <= 15


def _emails(text: str) -> Iterator[tuple[int, int]]:
    free, at = 0, text.find("@")
    while at >= 0:
        before = text[free:at]
        local = len(before) - len(before.rstrip(_LOCAL))
        found = _DOMAIN.match(text, at + 1) if local else None
        if found:
            yield at - local, found.end()
        free = found.end() if found else at + 1
        at = text.find("@", free)


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """The contract's spans, by kind and then start."""
    out = []
    if "@" in text:
        out += [("email", a, z) for a, z in _emails(text)]
    if _TRIGGER.search(text):
        for kind, pattern in (("ip", _IP), ("card", _CARD), ("phone", _PHONE)):
            out += [(kind, m.start(), m.end()) for m in pattern.finditer(text) if holds(kind, m[0])]
    return out


# ---- the tagger -------------------------------------------------------------------------------


def codes(text: str) -> np.ndarray:
    """Character classes: ASCII characters are themselves, other letters and other signs share one each."""
    points = np.frombuffer(text.encode("utf-32-le"), np.uint32)
    return np.where(points < 128, points, np.where(points < 0x250, 128, 129)).astype(np.int64)


def labelled_text(rng: random.Random) -> tuple[str, list[tuple[str, int, int]]]:
    """One written training text with its spans: words, distracting numbers and entities."""
    low = lambda: "".join(rng.choice("aaeeeiioourstnnlhdcmbfgpvwyzkjxq" + "éçßäöüñóè" * (rng.random() < 0.3)) for _ in range(rng.randint(1, 10)))
    word = lambda: low() if rng.random() < 0.8 else rng.choice((low().capitalize(), low().upper(), low()[:3] + "-" + low()))
    num = lambda n: "".join(rng.choice("0123456789") for _ in range(n))

    def card() -> str:
        body = num(rng.choice((15, 15, 15, 14, 12, 18)))
        body += next(c for c in "0123456789" if luhn(body + c))
        gap = rng.choice(("", "", " ", "-"))
        return gap.join(body[i : i + 4] for i in range(0, len(body), 4))

    def entity(kind: str) -> str:
        if kind == "email":
            at, dot = rng.choice((("@", "."), ("@", "."), ("@", "."), (" [at] ", " [dot] "), ("(at)", "."), (" (at) ", " (dot) "), ("[at]", "[dot]")))
            host = f"{rng.choice(('mail', 'post', 'x', low()))}{rng.choice(('', num(1)))}.{rng.choice(('example.com', 'net', 'org', 'example.org'))}"
            return rng.choice((low(), num(2), low() + "." + low())).replace(".", dot if dot == "." else ".") + at + host.replace(".", dot)
        if kind == "ip":
            return rng.choice((".", ".", ".", "[.]", "(.)")).join(str(rng.randint(0, 255)) for _ in range(4))
        if kind == "card":
            return card()
        return rng.choice((f"+{rng.randint(1, 99)} ({num(3)}) {num(3)}-{num(4)}", f"+{num(2)} {num(3)} {num(3)} {num(3)}", f"+{num(11)}", f"({num(3)}) {num(3)}-{num(4)}", f"00{num(2)} {num(3)} {num(3)} {num(3)}", f"{num(3)}-{num(3)}-{num(4)}"))

    text, spans = "", []
    for _ in range(rng.randint(8, 18)):
        kind = rng.random()
        if kind < 0.22:
            name = rng.choice(KINDS)
            lead = rng.choice(("", "", "", num(rng.randint(1, 3)) + " ")) if name in ("card", "ip") else ""
            text += lead
            for more in range(rng.choice((1, 1, 1, 2)) if name == "card" else 1):  # cards side by side
                shown = (" " if more else "") + entity(name)
                spans.append((name, len(text) + (more > 0), len(text) + len(shown)))
                text += shown
        elif kind < 0.34:
            text += rng.choice(("(" + word() + ")", "[" + word() + "]", word() + ".", "at", "dot", num(rng.randint(1, 6)), f"{num(1)}.{num(2)}", f"{num(4)}-{num(2)}-{num(2)}", f"{num(3)}.{num(3)}", f"v{num(1)}.{num(1)}.{num(1)}", 'token = "' + "".join(rng.choice("0123456789abcdef") for _ in range(20)) + '"', f"@{word()}", f"{word()} @ {word()}"))
        else:
            text += word()
        text += rng.choice((" ", " ", " ", " ", ", ", ". ", "\n", "### ", "&&& ", "!! ", " | ", "*** ", "%%% ", ": ", "? ", "; "))
    return text, spans


def tags_of(length: int, spans: list[tuple[str, int, int]]) -> np.ndarray:
    y = np.zeros(length, np.int64)
    for kind, a, z in spans:
        k = 1 + 2 * KINDS.index(kind)
        y[a:z] = k + 1
        y[a] = k
    return y


def _allowed() -> np.ndarray:
    """Transitions that exist: an inside tag follows its own kind only."""
    ok = np.zeros((TAGS, TAGS))
    for k in range(2, TAGS, 2):
        ok[:, k] = -1e4
        ok[k - 1, k] = ok[k, k] = 0
    return ok


def _squash(x: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        return 1 / (1 + np.exp(-x))


class Tagger:
    def __init__(self, seed: int = SEED):
        rng = np.random.default_rng(seed)
        h = HIDDEN
        self.p = {"E": rng.normal(0, 0.3, (130, EMBED)), "O": rng.normal(0, 0.2, (2 * h, TAGS)), "b": np.zeros(TAGS), "A": np.zeros((TAGS, TAGS))}
        for d in "fb":
            self.p |= {f"W{d}": rng.normal(0, 0.3, (EMBED, 4 * h)), f"U{d}": rng.normal(0, 0.2, (h, 4 * h)), f"c{d}": np.concatenate([np.zeros(h), np.ones(h), np.zeros(2 * h)])}

    def _pass(self, x: np.ndarray, d: str, keep: bool) -> tuple[np.ndarray, list]:
        """One direction over (time, batch) codes; gates in the order input, forget, output, candidate."""
        h_n, (steps, n) = HIDDEN, x.shape
        ready = (self.p["E"] @ self.p[f"W{d}"] + self.p[f"c{d}"]).astype(self.kind)
        u = self.p[f"U{d}"].astype(self.kind)
        h, c, out, tape = np.zeros((n, h_n), self.kind), np.zeros((n, h_n), self.kind), np.zeros((steps, n, h_n), self.kind), []
        for t in range(steps) if d == "f" else range(steps - 1, -1, -1):
            z = ready[x[t]] + h @ u
            s = _squash(z[:, : 3 * h_n])
            i, f, o, g = s[:, :h_n], s[:, h_n : 2 * h_n], s[:, 2 * h_n :], np.tanh(z[:, 3 * h_n :])
            new = f * c + i * g
            q = np.tanh(new)
            if keep:
                tape.append((t, i, f, o, g, c, q, h))
            c, h = new, o * q
            out[t] = h
        return out, tape

    kind = np.float64

    def emissions(self, x: np.ndarray) -> np.ndarray:
        """(batch, time) codes to (batch, time, tag) scores."""
        y = np.concatenate([self._pass(x.T, d, False)[0] for d in "fb"], axis=2)
        return (y @ self.p["O"].astype(self.kind) + self.p["b"].astype(self.kind)).transpose(1, 0, 2)

    def _crf(self, e: np.ndarray, y: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
        """Loss, and gradients by emissions (time, batch, tag) and transitions."""
        steps, n, k = e.shape
        trans = self.p["A"] + _allowed()
        lse = lambda v, axis: (m := v.max(axis=axis, keepdims=True)).squeeze(axis) + np.log(np.exp(v - m).sum(axis=axis))
        alpha, beta = np.zeros_like(e), np.zeros_like(e)
        alpha[0] = e[0]
        for t in range(1, steps):
            alpha[t] = e[t] + lse(alpha[t - 1][:, :, None] + trans[None], 1)
        for t in range(steps - 2, -1, -1):
            beta[t] = lse(trans[None] + (e[t + 1] + beta[t + 1])[:, None, :], 2)
        z = lse(alpha[-1], 1)
        de = np.exp(alpha + beta - z[None, :, None])
        pair = np.exp(alpha[:-1, :, :, None] + trans[None, None] + (e[1:] + beta[1:])[:, :, None, :] - z[None, :, None, None])
        da = pair.sum(axis=(0, 1))
        at, who = np.arange(steps)[:, None], np.arange(n)[None, :]
        gold = e[at, who, y].sum() + trans[y[:-1], y[1:]].sum()
        de[at, who, y] -= 1
        np.add.at(da, (y[:-1].ravel(), y[1:].ravel()), -1)
        return float(z.sum() - gold), de, da

    def gradients(self, x: np.ndarray, y: np.ndarray) -> tuple[float, dict]:
        x, y = x.T, y.T
        tapes = {d: self._pass(x, d, True) for d in "fb"}
        both = np.concatenate([tapes["f"][0], tapes["b"][0]], axis=2)
        loss, de, da = self._crf(both @ self.p["O"] + self.p["b"], y)
        h_n = HIDDEN
        g = {"A": da, "b": de.sum(axis=(0, 1)), "O": np.einsum("tnh,tnk->hk", both, de), "E": np.zeros_like(self.p["E"])}
        d_both = de @ self.p["O"].T
        for k, d in enumerate("fb"):
            u, w = self.p[f"U{d}"], self.p[f"W{d}"]
            dz_all = np.zeros((*x.shape, 4 * h_n))
            du, dh, dc = np.zeros_like(u), np.zeros((x.shape[1], h_n)), np.zeros((x.shape[1], h_n))
            for t, i, f, o, c_, c_old, q, h_old in reversed(tapes[d][1]):
                dh = dh + d_both[t, :, k * h_n : (k + 1) * h_n]
                dc = dc + dh * o * (1 - q * q)
                dz = np.concatenate([dc * c_ * i * (1 - i), dc * c_old * f * (1 - f), dh * q * o * (1 - o), dc * i * (1 - c_ * c_)], axis=1)
                dz_all[t] = dz
                du += h_old.T @ dz
                dh, dc = dz @ u.T, dc * f
            by_code = np.zeros((130, 4 * h_n))
            np.add.at(by_code, x.ravel(), dz_all.reshape(-1, 4 * h_n))
            g |= {f"U{d}": du, f"W{d}": self.p["E"].T @ by_code, f"c{d}": by_code.sum(axis=0)}
            g["E"] += by_code @ w.T
        return loss / y.size, {name: v / y.size for name, v in g.items()}

    def train(self, steps: int = STEPS, seed: int = SEED) -> float:
        rng = random.Random(seed)
        m, v = ({k: np.zeros_like(x) for k, x in self.p.items()} for _ in range(2))
        loss = 0.0
        for s in range(1, steps + 1):
            xs, ys = [], []
            while len(xs) < BATCH:
                text, spans = labelled_text(rng)
                y = tags_of(len(text), spans)
                at = rng.randint(0, max(0, len(text) - TRAIN_WIDTH))
                if len(text) >= TRAIN_WIDTH and (at == 0 or y[at] % 2 == 1 or y[at] == 0):
                    xs.append(codes(text)[at : at + TRAIN_WIDTH]), ys.append(y[at : at + TRAIN_WIDTH])
            loss, g = self.gradients(np.array(xs), np.array(ys))
            rate = RATE * min(1, 2 * (1 - s / (steps + 1)))
            for k in self.p:
                m[k] = 0.9 * m[k] + 0.1 * g[k]
                v[k] = 0.99 * v[k] + 0.01 * g[k] ** 2
                self.p[k] -= rate * (m[k] / (1 - 0.9**s)) / (np.sqrt(v[k] / (1 - 0.99**s)) + 1e-8)
        return loss

    def viterbi(self, e: np.ndarray) -> np.ndarray:
        """Best tags of (batch, time, tag) emissions. Outside and begin tags follow any tag, an inside tag two only."""
        trans = (self.p["A"] + _allowed()).astype(e.dtype)
        n, steps, _ = e.shape
        free, own, begin = [0, *range(1, TAGS, 2)], list(range(2, TAGS, 2)), list(range(1, TAGS, 2))
        into = trans[:, free, None]
        stay, enter = trans[own, own, None], trans[begin, own, None]
        best = np.empty((steps, TAGS, n), e.dtype)
        best[0] = e[:, 0].T
        best[0, own] -= 1e4
        for t in range(1, steps):
            last, now = best[t - 1], best[t]
            now[free] = (last[:, None] + into).max(axis=0)
            now[own] = np.maximum(last[own] + stay, last[begin] + enter)
            now += e[:, t].T
        tags = np.zeros((n, steps), np.int64)
        tags[:, -1] = best[-1].argmax(axis=0)
        for t in range(steps - 1, 0, -1):
            tags[:, t - 1] = (best[t - 1] + trans[:, tags[:, t]]).argmax(axis=0)
        return tags


@functools.lru_cache(maxsize=1)
def trained() -> Tagger:
    """The tagger after training; the same weights in every process."""
    t = Tagger()
    t.train()
    t.kind = np.float32  # half the time of doubles; training has them
    return t


_EDGE = np.minimum(np.arange(1, WIDTH + 1), np.arange(WIDTH, 0, -1)).astype(np.float32)


def _blocks(length: int, most: int) -> list[tuple[int, int, int]]:
    """(begin, end of the core, end with overlap) of the pieces of a run."""
    return [(a, min(length, a + most), min(length, a + most + OVERLAP)) for a in range(0, length, most)]


def _emissions(flat: np.ndarray, starts: list[int], lengths: list[int], tagger: Tagger, at_once: int, every: bool = False) -> np.ndarray:
    """Mean emissions of every character of texts that lie in flat, WIDTH blanks after each."""
    first, second = [], []
    signs = np.concatenate([[0], np.cumsum(_SIGNS[flat])])
    for s, n in zip(starts, lengths):
        grid = np.arange(s, s + max(1, n - (WIDTH - STEP)), STEP)
        held = signs[np.minimum(s + n, grid + WIDTH + REACH)] > signs[np.maximum(s, grid - REACH)]
        first.append(grid[::2][held[::2] | every]), second.append(grid[1::2][held[1::2] | every])
    total, weight = np.zeros((len(flat), TAGS), np.float32), np.zeros(len(flat), np.float32)
    half = sum(map(len, first))
    at = np.concatenate([np.zeros(0, np.int64), *first, *second])
    for i in range(0, len(at), at_once):
        where = at[i : i + at_once, None] + np.arange(WIDTH)
        e = tagger.emissions(flat[where])
        e *= _EDGE[:, None]
        cut = min(len(where), max(0, half - i))
        for part in (slice(0, cut), slice(cut, len(where))):  # windows of one half don't overlap
            total[where[part]] += e[part]
            weight[where[part]] += _EDGE
    total /= np.maximum(weight, 1e-9)[:, None]
    total[weight == 0, 1:] = -50.0
    return total


def _tagged(e: np.ndarray, tagger: Tagger) -> Iterator[tuple[int, int, int]]:
    """(begin, end, entity tag) of the decoded spans of one run of emissions."""
    found = [np.zeros((0, 2), np.int64)]
    trans = tagger.p["A"]
    # Leaving an entity for another one at once costs a transition of its own; the least of both exits is taken.
    out_of = np.maximum(trans[:, 0], trans[:, 1::2].max(axis=1) - trans[0, 1::2].min() + trans[0, 0])
    for b in range(1, TAGS, 2):
        stay = max(float(trans[b, b + 1]), float(trans[b + 1, b + 1])) - trans[0, 0]
        toll = trans[0, 0] - float(trans[0, b]) - float(max(out_of[b], out_of[b + 1])) + stay
        run = np.cumsum(np.maximum(e[:, b], e[:, b + 1]) - e[:, 0] + stay, dtype=np.float64)
        least = np.minimum(np.minimum.accumulate(run), 0)
        near = np.flatnonzero(run - least > max(0.0, toll))  # the greatest sum of a run that ends here
        if len(near):
            fresh = np.append(True, least[near][1:] < least[near][:-1])  # a new excursion above the least sum so far
            first, last = near[fresh], near[np.append(np.flatnonzero(fresh)[1:] - 1, len(near) - 1)]
            rise = np.searchsorted(-least, -least[first], side="left")  # where that least sum was reached
            found.append(np.stack([np.minimum(rise, first), last], axis=1))
    regions = np.concatenate(found)
    if not len(regions):
        return
    regions = regions[np.argsort(regions[:, 0], kind="stable")]
    lows, highs = np.maximum(0, regions[:, 0] - PAD), np.maximum.accumulate(np.minimum(len(e), regions[:, 1] + PAD + 1))
    joins = np.flatnonzero(lows[1:] > highs[:-1])
    lows, highs = lows[np.append(0, joins + 1)], highs[np.append(joins, len(highs) - 1)]
    rows = [(lo + a, lo + core, lo + z) for lo, hi in zip(lows.tolist(), highs.tolist()) for a, core, z in _blocks(hi - lo, BLOCK)]
    rows.sort(key=lambda r: r[2] - r[0])
    k = 0
    while k < len(rows):
        longest = rows[k][2] - rows[k][0]
        m = k + 1
        while m < len(rows) and rows[m][2] - rows[m][0] <= 1.5 * longest + 16 and (m - k) * (rows[m][2] - rows[m][0]) < 200_000:
            m += 1
        group = rows[k:m]
        size = max(z - a for a, _, z in group)
        block = np.zeros((len(group), size, TAGS), np.float32)
        block[:, :, 1:] = -50.0
        for r, (a, _, z) in enumerate(group):
            block[r, : z - a] = e[a:z]
        for (a, core, z), y in zip(group, tagger.viterbi(block)):
            for i in np.flatnonzero(y[: core - a] % 2 == 1).tolist():
                j = i + 1
                while j < z - a and y[j] == y[i] + 1:
                    j += 1
                yield a + i, a + j, int(y[i])
        k = m


def model_spans(texts: list[str], tagger: Tagger, at_once: int = 1024, every: bool = False) -> list[list[tuple[str, int, int]]]:
    """The tagger's spans per text, by start."""
    out: list[list[tuple[str, int, int]]] = [[] for _ in texts]
    pieces = [(k, a, core, z) for k, t in enumerate(texts) for a, core, z in _blocks(len(t), PIECE)]
    k = 0
    while k < len(pieces):
        m, size = k, 0
        while m < len(pieces) and (m == k or size + pieces[m][3] - pieces[m][1] <= PIECE):
            size += pieces[m][3] - pieces[m][1]
            m += 1
        lengths = [z - a for _, a, _, z in pieces[k:m]]
        starts = np.concatenate([[0], np.cumsum(np.array(lengths) + WIDTH)]).tolist()
        flat = np.full(starts[-1], 32, np.int64)
        for s, (t, a, _, z) in zip(starts, pieces[k:m]):
            flat[s : s + z - a] = codes(texts[t][a:z])
        e = _emissions(flat, starts[:-1], lengths, tagger, at_once, every)
        order = np.array(starts)
        for i, j, tag in _tagged(e, tagger):
            r = int(np.searchsorted(order, i, side="right")) - 1
            t, a, core, z = pieces[k + r]
            i, j = i - starts[r] + a, min(j - starts[r] + a, z)
            if i < core and i < j:
                out[t].append((KINDS[(tag - 1) // 2], i, j))
        k = m
    for spans in out:
        spans.sort(key=lambda x: (x[1], x[2]))
    return out


_AT, _DOT = re.compile(r"\s?[\[(]\s?(?:at|AT|@)\s?[\])]\s?"), re.compile(r"\s?[\[(]\s?(?:dot|DOT|[.])\s?[\])]\s?")
_GROUPS = re.compile(r"[0-9]+")
_PLAIN_PHONE = re.compile(r"(?:\([0-9]{2,4}\)[\x20.-]?|00[0-9]{1,3}[\x20.-]|[0-9]{3}[\x20.-])[0-9]{2,4}(?:[\x20.-][0-9]{2,4})+")


def settled(kind: str, text: str, a: int, z: int) -> list[tuple[int, int]]:
    """The parts of a tagged span that are of its kind: trimmed, spelt-out signs put back, cards cut from rows of digits."""
    digit = lambda k: 0 <= k < len(text) and "0" <= text[k] <= "9"
    if kind == "card":
        groups = [(a + m.start(), a + m.end()) for m in _GROUPS.finditer(text[a:z])]
        if groups:  # digits that the tagger cut off belong to the outer groups
            lo, hi = groups[0][0], groups[-1][1]
            while digit(lo - 1):
                lo -= 1
            while digit(hi):
                hi += 1
            groups[0], groups[-1] = (lo, groups[0][1]), (groups[-1][0], hi) if len(groups) > 1 else (lo, hi)
        out, i = [], 0
        while i < len(groups):
            took = 0
            for j in range(i, min(len(groups), i + 19)):
                if j > i and (groups[j][0] - groups[j - 1][1] != 1 or text[groups[j - 1][1]] not in " -"):
                    break
                d = _digits(text[groups[i][0] : groups[j][1]])
                if len(d) > 19:
                    break
                if len(d) >= 13 and luhn(d):
                    took = j + 1
            if took:
                out.append((groups[i][0], groups[took - 1][1]))
            i = took or i + 1
        return out
    ends = {"email": _LOCAL + "])", "ip": "0123456789", "phone": "+(0123456789"}[kind]
    while a < z and text[a] not in ends:
        a += 1
    while a < z and (text[z - 1] not in ends or (kind == "email" and text[z - 1] in "._%+])")):
        z -= 1
    if a >= z or digit(a - 1) or digit(z):
        return []
    if kind == "phone":
        n = len(_digits(text[a:z]))
        return [(a, z)] if holds(kind, text[a:z]) or (9 <= n <= 15 and _PLAIN_PHONE.fullmatch(text, a, z)) else []
    plain = _DOT.sub(".", _AT.sub("@", text[a:z]))
    return [(a, z)] if holds(kind, plain) else []


def find(texts: list[str], tagger: Tagger) -> list[tuple[list, list]]:
    """Per text: base spans, and all spans, both by kind and then start."""
    out = []
    for text, guessed in zip(texts, model_spans(texts, tagger)):
        out.append(merged(text, base_spans(text), guessed))
    return out


def merged(text: str, base: list[tuple[str, int, int]], guessed: list[tuple[str, int, int]]) -> tuple[list, list]:
    """Base spans, and they with the tagger's that hold and share no character with them or each other."""
    taken = sorted((a, z) for _, a, z in base)
    heads, reach, top = [a for a, _ in taken], [], 0
    for _, z in taken:
        top = max(top, z)
        reach.append(top)
    added, free = [], 0
    for kind, a, z in guessed:
        for lo, hi in settled(kind, text, a, z):
            k = bisect.bisect_left(heads, hi)  # base spans that begin before this one ends
            if lo >= free and (k == 0 or reach[k - 1] <= lo):
                added.append((kind, lo, hi))
                free = hi
    return base, sorted(base + added, key=lambda s: (KINDS.index(s[0]), s[1]))


def shown(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{z}" for k, a, z in spans)


CHUNK_CHARS = 1_000_000


def _chunks(texts: list[str]) -> Iterator[list[str]]:
    held, size = [], 0
    for t in texts:
        if held and size + len(t) > CHUNK_CHARS:
            yield held
            held, size = [], 0
        held.append(t)
        size += len(t)
    if held:
        yield held


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: id, the number of spans of each kind found by the patterns, base and spans as text."""
    shared = docs.sparkSession.sparkContext.broadcast(trained())
    schema = T.StructType([T.StructField(id_col, docs.schema[id_col].dataType), *(T.StructField(f"n_{k}", T.LongType()) for k in KINDS), T.StructField("base", T.StringType()), T.StructField("spans", T.StringType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = [r for c in _chunks(as_texts(b.column(1))) for r in find(c, shared.value)]
            counts = [pa.array([sum(s[0] == k for s in base) for base, _ in rows], pa.int64()) for k in KINDS]
            texts = [pa.array([shown(r[j]) for r in rows], pa.string()) for j in (0, 1)]
            yield pa.RecordBatch.from_arrays([b.column(0), *counts, *texts], names=schema.names)

    return docs.select(id_col, F.col(text_col).cast("string")).mapInArrow(run, schema)


def redact(docs: DataFrame, text_col: str = "text", mark: str = "<{}>") -> DataFrame:
    """The same columns, with every span replaced by its kind's mark; null texts stay null."""
    shared = docs.sparkSession.sparkContext.broadcast(trained())
    names = docs.columns
    at = names.index(text_col)

    def clean(text: str, spans: list) -> str:
        parts, free = [], 0
        for kind, a, z in sorted(spans, key=lambda s: (s[1], -s[2])):
            if z > free:
                parts += [text[free : max(a, free)], mark.format(kind)]
                free = z
        return "".join([*parts, text[free:]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = as_texts(b.column(at))
            found = [r for c in _chunks(texts) for r in find(c, shared.value)]
            null = b.column(at).is_null().to_pylist()
            new = [None if gone else clean(t, spans) if spans else t for t, (_, spans), gone in zip(texts, found, null)]
            columns = list(b.columns)
            columns[at] = pa.array(new, pa.string())
            yield pa.RecordBatch.from_arrays(columns, names=names)

    return docs.mapInArrow(run, docs.schema)
