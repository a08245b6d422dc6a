"""Personal data: fixed patterns, and a character BiLSTM with CRF transitions that adds what the patterns miss.

Both are numpy. The network is trained from labelled spans: the patterns' matches in a bounded sample, and generated forms beyond the
patterns (``written``) in texts of the sample, beside numbers and handles that are none (``other``). A text is cut into overlapping windows
on a grid; each character takes its tag from the window in which it lies most centrally, and spans are drawn from the tags of the
whole text. A span counts only if it holds a digit or an @, so a window is evaluated if it has one in its middle or if a span reaches it
from its neighbour: the result is that of all windows. What comes out is stretched to whole words and numbers and checked (``plausible``).
"""

from __future__ import annotations

import itertools
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqstat.llm.shared import sample_rows
from seqstat.llm.spans import Kind, Span, ordered, outside

#: The contract's patterns (lookbehinds only spare repeated attempts inside one run).
DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
IP = re.compile(r"(?<![0-9])[0-9]+(?:\.[0-9]+){3}")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
DIGIT = re.compile(r"[0-9]")
BASE = ["email", "ip", "card", "phone"]
NAMES = BASE + [f"lstm_{k}" for k in BASE]


def digits_of(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def luhn(number: str) -> bool:
    total = sum(map(int, number[-1::-2])) + sum(sum(divmod(2 * int(c), 10)) for c in number[-2::-2])
    return total % 10 == 0


def card_like(m: re.Match) -> bool:
    number = digits_of(m[0])
    return 14 <= len(number) <= 19 and luhn(number)


NUMBERS = [
    Kind("ip", IP, lambda m: all(len(p := x.lstrip("0")) <= 3 and int(p or 0) <= 255 for x in m[0].split("."))),
    Kind("card", CARD, card_like),
    Kind("phone", PHONE, lambda m: 10 <= len(digits_of(m[0])) <= 15),
]


def emails(text: str) -> Iterator[Span]:
    """The pattern's matches, found from each @ outwards, so that long runs without one cost nothing."""
    past, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > past and text[start - 1] in LOCAL:
            start -= 1
        if start < at and (m := DOMAIN.match(text, at + 1)):
            yield start, m.end(), "email"
            past = m.end()
        at = text.find("@", max(at + 1, past))


def base_spans(text: str) -> list[Span]:
    found = list(emails(text)) if "@" in text else []
    if DIGIT.search(text):
        for kind in NUMBERS:
            found += kind.find(text)
    return ordered(found, NAMES)


PUNCTUATION = "@.+-() _%,:;/#\n\"'"
CLASSES = 5 + len(PUNCTUATION)
_CLASS = np.full(257, 4, np.uint8)
_CLASS[[*range(97, 123)]], _CLASS[[*range(65, 91)]], _CLASS[[*range(48, 58)]] = 1, 2, 3
_CLASS[[ord(c) for c in PUNCTUATION]] = 5 + np.arange(len(PUNCTUATION))
_CLASS[256] = 1  # letters beyond Latin-1, for the most part
TAGS = 1 + 2 * len(BASE)


def classes(text: str) -> np.ndarray:
    return _CLASS[np.minimum(np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32), 256)]


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


def log_sum(x: np.ndarray, axis: int) -> np.ndarray:
    most = x.max(axis=axis, keepdims=True)
    return np.squeeze(most, axis) + np.log(np.exp(x - most).sum(axis=axis))


class Tagger:
    """A BiLSTM over character classes with a CRF over tags; class 0 pads."""

    def __init__(self, hidden: int = 20, seed: int = 11):
        rng = np.random.default_rng(seed)
        h, draw = hidden, lambda *s, scale=0.3: rng.normal(0, scale, s).astype(np.float32)
        self.hidden = hidden
        self.weights = {f"{k}{d}": v for d in "fb" for k, v in (("x", draw(CLASSES, 4 * h)), ("h", draw(h, 4 * h)), ("c", np.concatenate([np.zeros(h), np.ones(h), np.zeros(2 * h)]).astype(np.float32)))}
        self.weights |= {"o": draw(2 * h, TAGS), "q": np.zeros(TAGS, np.float32), "t": draw(TAGS, TAGS, scale=0.1)}

    def lstm(self, x: np.ndarray, d: str, keep: bool) -> tuple[np.ndarray, list]:
        n, steps, h = *x.shape, self.hidden
        wx, wh, bias = (self.weights[k + d] for k in "xhc")
        state, cell = np.zeros((n, h), np.float32), np.zeros((n, h), np.float32)
        out, tape = np.empty((steps, n, h), np.float32), []
        for s in range(steps) if d == "f" else range(steps - 1, -1, -1):
            g = wx[x[:, s]] + state @ wh + bias
            i, f, o = (sigmoid(g[:, k * h : (k + 1) * h]) for k in range(3))
            u = np.tanh(g[:, 3 * h :])
            before, last = cell, state
            cell = f * cell + i * u
            tc = np.tanh(cell)
            state = o * tc
            out[s] = state
            if keep:
                tape.append((s, i, f, o, u, before, last, tc))
        return out, tape

    def emissions(self, x: np.ndarray, keep: bool = False):
        forward, tf = self.lstm(x, "f", keep)
        backward, tb = self.lstm(x, "b", keep)
        both = np.concatenate([forward, backward], axis=2)
        return both @ self.weights["o"] + self.weights["q"], both, tf, tb

    def decode(self, x: np.ndarray) -> np.ndarray:
        """The best tags of each row of ``x`` by Viterbi."""
        scores = self.emissions(x)[0]
        best, back = scores[0], np.empty(scores.shape, np.int8)
        for s in range(1, len(scores)):
            paths = best[:, :, None] + self.weights["t"]
            back[s] = paths.argmax(axis=1)
            best = paths.max(axis=1) + scores[s]
        tags = np.empty(x.shape, np.int8)
        rows = np.arange(len(x))
        tags[:, -1] = best.argmax(axis=1)
        for s in range(len(scores) - 1, 0, -1):
            tags[:, s - 1] = back[s][rows, tags[:, s]]
        return tags

    def gradients(self, x: np.ndarray, y: np.ndarray) -> tuple[float, dict]:
        """Mean negative log-likelihood of the tags and its gradients."""
        scores, both, tf, tb = self.emissions(x, True)
        steps, n, _ = scores.shape
        t = self.weights["t"]
        alpha, beta = np.empty_like(scores), np.zeros_like(scores)
        alpha[0] = scores[0]
        for s in range(1, steps):
            alpha[s] = log_sum(alpha[s - 1][:, :, None] + t, 1) + scores[s]
        for s in range(steps - 2, -1, -1):
            beta[s] = log_sum(t + (scores[s + 1] + beta[s + 1])[:, None, :], 2)
        z = log_sum(alpha[-1], 1)
        rows = np.arange(n)
        gold = sum(scores[s, rows, y[:, s]] for s in range(steps)) + sum(t[y[:, s - 1], y[:, s]] for s in range(1, steps))
        ds = np.exp(alpha + beta - z[None, :, None])
        dt = np.zeros_like(t)
        for s in range(1, steps):
            dt += np.exp(alpha[s - 1][:, :, None] + t + (scores[s] + beta[s])[:, None, :] - z[:, None, None]).sum(0)
            np.add.at(dt, (y[:, s - 1], y[:, s]), -1)
        for s in range(steps):
            ds[s, rows, y[:, s]] -= 1
        ds /= n
        out = {"t": dt / n, "o": np.einsum("snk,snt->kt", both, ds), "q": ds.sum((0, 1))}
        dh = ds @ self.weights["o"].T
        h = self.hidden
        for d, tape, dout in (("f", tf, dh[:, :, :h]), ("b", tb, dh[:, :, h:])):
            wx, wh = np.zeros_like(self.weights["x" + d]), np.zeros_like(self.weights["h" + d])
            bias = np.zeros(4 * h, np.float32)
            ahead, dcell = np.zeros((n, h), np.float32), np.zeros((n, h), np.float32)
            for s, i, f, o, u, before, last, tc in reversed(tape):
                dstate = dout[s] + ahead
                dcell = dcell + dstate * o * (1 - tc * tc)
                g = np.concatenate([dcell * u * i * (1 - i), dcell * before * f * (1 - f), dstate * tc * o * (1 - o), dcell * i * (1 - u * u)], axis=1)
                np.add.at(wx, x[:, s], g)
                wh += last.T @ g
                bias += g.sum(0)
                ahead, dcell = g @ self.weights["h" + d].T, dcell * f
            out |= {"x" + d: wx, "h" + d: wh, "c" + d: bias}
        return float((z - gold).mean()), out

    def fit(self, x: np.ndarray, y: np.ndarray, turns: int = 900, batch: int = 96, rate: float = 0.01, seed: int = 5) -> float:
        """Adam on batches drawn with a fixed seed; returns the last loss."""
        rng = np.random.default_rng(seed)
        m, v = ({k: np.zeros_like(w) for k, w in self.weights.items()} for _ in range(2))
        loss = 0.0
        for turn in range(1, turns + 1):
            at = rng.integers(0, len(x), batch)
            loss, grads = self.gradients(x[at], y[at])
            for k, g in grads.items():
                g = np.clip(g, -1, 1)
                m[k] = 0.9 * m[k] + 0.1 * g
                v[k] = 0.999 * v[k] + 0.001 * g * g
                step = rate * (1 - turn / (turns + 20)) * (m[k] / (1 - 0.9**turn)) / (np.sqrt(v[k] / (1 - 0.999**turn)) + 1e-6)
                self.weights[k] = (self.weights[k] - step).astype(np.float32)
        return loss


@dataclass(frozen=True)
class Windows:
    width: int = 64
    stride: int = 32

    def cells(self, n: int) -> int:
        """Windows of a text of n characters."""
        return max(1, -(-(n - self.width + self.stride) // self.stride))

    def owned(self, cell: int, n: int) -> tuple[int, int]:
        """The characters that take their tags from a window: those nearer to its middle than to any other's."""
        edge = (self.width - self.stride) // 2
        return cell * self.stride + edge if cell else 0, min(n, (cell + 1) * self.stride + edge) if cell + 1 < self.cells(n) else n

    def cut(self, whole: np.ndarray, cell: int) -> np.ndarray:
        part = whole[cell * self.stride : cell * self.stride + self.width]
        return np.pad(part, (0, self.width - len(part)))


DOUBTFUL = re.compile(r"@|(?:[0-9][^A-Za-z0-9@]{0,3}){9,}[0-9]|[0-9]{1,3}(?:\W{1,3}[0-9]{1,3}){3}")


def tags_of(n: int, spans: list[Span]) -> np.ndarray:
    tags = np.zeros(n, np.int64)
    for a, b, name in spans:
        tags[a], tags[a + 1 : b] = 1 + 2 * BASE.index(name), 2 + 2 * BASE.index(name)
    return tags


def stacked(xs: list[np.ndarray], width: int) -> np.ndarray:
    return np.stack([np.pad(x[:width], (0, max(0, width - len(x)))) for x in xs]) if xs else np.zeros((0, width), np.int64)


def labelled(texts: list[str], width: int = 64, most: int = 4000, seed: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Windows and tags: each base span at a random place of a window, other digits, and stretches without any. Windows that hold what may
    be an unlabelled span (``DOUBTFUL`` outside the base spans) are left out, so that they don't teach that it is none."""
    rng = np.random.default_rng(seed)
    xs, ys = [], []
    for text in texts:
        spans = base_spans(text)
        tags, whole = tags_of(len(text), spans), classes(text)
        places = [max(0, a - int(rng.integers(0, width - 8))) for a, _, _ in spans]
        places += [max(0, m.start() - int(rng.integers(0, width - 8))) for m in itertools.islice(DIGIT.finditer(text), 4)]
        places += [int(rng.integers(0, max(1, len(text) - width))) for _ in range(2)]
        doubts = outside([(m.start(), m.end(), "") for m in DOUBTFUL.finditer(text)], spans)
        places = [p for p in places if not any(a < p + width and p < b for a, b, _ in doubts)]
        xs += [whole[p : p + width] for p in places]
        ys += [tags[p : p + width] for p in places]
        if len(xs) >= most:
            break
    return stacked(xs, width), stacked(ys, width)


def luhn_number(rng: np.random.Generator, n: int) -> str:
    head = "".join(map(str, rng.integers(0, 10, n - 1)))
    return next(head + c for c in "0123456789" if luhn(head + c))


def fill(rng: np.random.Generator, form: str) -> str:
    """A form with digits for # and letters for ?."""
    return "".join(str(rng.integers(0, 10)) if c == "#" else chr(97 + rng.integers(0, 26)) if c == "?" else c for c in form)


def grouped(number: str, by: str) -> str:
    return by.join(number[i : i + 4] for i in range(0, len(number), 4))


#: Forms beyond the patterns: national numbers without a plus, hosts without a dot, spaced or defanged addresses.
PHONES = ["(###) ###-####", "###-###-####", "###.###.####", "(###) ### ####", "(###)###-####", "00## ## #######", "0## / #######", "0##/#######", "+#/###/###/####", "0### ### ####", "1-###-###-####"]
MAILS = ["{} @ {}.com", "{}@{}", "{}@localhost", "{} @ {}.example.org", "{}[@]{}.net", "{}@{}-host"]
ADDRESSES = ["{}[.]{}[.]{}[.]{}", "{}[.]{}.{}.{}", "{} . {} . {} . {}", "{}(.){}(.){}(.){}"]
SEPARATORS = [".", "/", "_", "  ", " - ", ":"]
#: Forms that are none of the kinds.
OTHERS = ["####-##-##", "##/##/####", "##:##:##", "$#,###.##", "##.#%", "v#.##.#", "#.#.#", "###-##-####", "INV-####-######", "978-#-##-######-#", "# ### ###", "##########", "@??????", "@????_??", "#####", "####", "####-##-## ##:##:##", "##.##.####", "ISSN ####-####", "#,###,###", "[##]", "(####)", "##-##", "+##", "+#.#%", "no. ###/####"]


def written(rng: np.random.Generator) -> tuple[str, str]:
    """(text, kind) of a span that no pattern finds whole."""
    kind = BASE[int(rng.integers(0, len(BASE)))]
    pick = lambda of: of[int(rng.integers(0, len(of)))]
    if kind == "email":
        name = fill(rng, pick(["????", "?????.??????", "?.??????", "??????##", "????_?????"]))
        return pick(MAILS).format(name, fill(rng, pick(["????", "???????", "?????????"]))), kind
    if kind == "ip":
        return pick(ADDRESSES).format(*rng.integers(0, 256, 4)), kind
    if kind == "card":
        return grouped(luhn_number(rng, pick([15, 16, 16, 16, 19])), pick(SEPARATORS)), kind
    return fill(rng, pick(PHONES)), kind


def other(rng: np.random.Generator) -> str:
    if rng.random() < 0.2:  # a card that its check digit refutes
        number = luhn_number(rng, 16)
        return grouped(number[:-1] + str((int(number[-1]) + int(rng.integers(1, 10))) % 10), ["", " ", "-", "."][int(rng.integers(0, 4))])
    return fill(rng, OTHERS[int(rng.integers(0, len(OTHERS)))])


def planted(texts: list[str], width: int = 64, n: int = 4000, seed: int = 19) -> tuple[np.ndarray, np.ndarray]:
    """Windows and tags: one or two forms each, of ``written`` or ``other``, at random places of the texts' stretches."""
    rng, xs, ys = np.random.default_rng(seed), [], []
    texts = [t for t in texts if t] or [""]
    for i in range(n):
        text = texts[i % len(texts)]
        at = int(rng.integers(0, max(1, len(text) - 2 * width)))
        around = DIGITS_OR_AT.sub("x", text[at : at + 2 * width])
        gaps = [m.end() for m in re.finditer(r"\s", around[: width - 8])] or [0]
        line, spans, past = "", [], 0
        for place in sorted(rng.choice(gaps, min(len(gaps), 1 + i % 2), replace=False).tolist()):
            form, kind = (other(rng), None) if rng.random() < 0.3 else written(rng)
            line += around[past:place]
            spans += [(len(line), len(line) + len(form), kind)] if kind else []
            line += form + ["", ".", ",", ";", ")"][int(rng.integers(0, 5))] + " "
            past = place
        line += around[past:]
        tags = tags_of(len(line), spans)
        xs.append(classes(line)[:width])
        ys.append(tags[:width])
    return stacked(xs, width), stacked(ys, width)


DIGITS_OR_AT = re.compile("[0-9@]")


def tag_texts(model: Tagger, texts: list[str], w: Windows, block: int = 2048, lazy: bool = True) -> Iterator[np.ndarray]:
    """Per text the tags of its characters. ``lazy`` evaluates a window if its own characters hold a digit or an @, or if a span
    of a neighbour goes on in it; characters of the others are tagged 0, and hold no span that counts."""
    whole = [classes(t) for t in texts]
    tags = [np.zeros(len(t), np.int8) for t in texts]
    edge, done, ask = (w.width - w.stride) // 2, set(), []
    for i, x in enumerate(whole):
        last = w.cells(len(x)) - 1
        at = np.flatnonzero((x == 3) | (x == 5)) if lazy else np.arange(len(x))  # digits and @
        ask += [(i, int(c)) for c in np.unique(np.clip((at - edge) // w.stride, 0, last))]
    while ask:
        done.update(ask)
        for first in range(0, len(ask), block):
            part = ask[first : first + block]
            for (i, c), got in zip(part, model.decode(np.stack([w.cut(whole[i], c) for i, c in part])), strict=True):
                a, b = w.owned(c, len(whole[i]))
                tags[i][a:b] = got[a - c * w.stride : b - c * w.stride]
        more = set()
        for i, c in ask:
            a, b = w.owned(c, len(whole[i]))
            if b < len(whole[i]) and tags[i][b - 1]:
                more.add((i, c + 1))
            if a and tags[i][a] and tags[i][a] % 2 == 0:  # inside a span that begins before
                more.add((i, c - 1))
        ask = sorted(more - done)
    yield from tags


MAIL = re.compile(r"[A-Za-z0-9._%+'-]+\s?[\[(]?@[\])]?\s?[A-Za-z0-9-]+(?:\s?\.\s?[A-Za-z0-9-]+)*")
NUMBER = re.compile(r"[0-9 ().+/-]+")


def stretched(text: str, a: int, b: int, kind: str) -> tuple[int, int]:
    """The span without blanks and stops at its ends, and with the whole of the word or number that it begins or ends in."""
    inside = (lambda c: c in LOCAL or c == "'") if kind == "email" else (lambda c: "0" <= c <= "9")
    while a < b and not (inside(text[a]) or kind == "phone" and text[a] in "+("):
        a += 1
    while a < b and not inside(text[b - 1]):
        b -= 1
    while a < b and a > 0 and inside(text[a - 1]) and inside(text[a]):
        a -= 1
    while a < b < len(text) and inside(text[b]):
        b += 1
    while kind == "email" and a < b and text[b - 1] in ".%+-_'":
        b -= 1
    return a, b


def plausible(kind: str, s: str) -> bool:
    """Checks that a form must pass whatever the network says: digits and their check sum, parts, a host."""
    digits = digits_of(s)
    if kind == "email":
        return MAIL.fullmatch(s) is not None and len(s.split("@")[0].strip(" [(")) >= 2 and len(s.split("@")[1].strip(" ])")) >= 3
    if kind == "ip":
        parts = re.findall("[0-9]+", s)
        return len(parts) == 4 and all(len(p) <= 3 and int(p) <= 255 for p in parts) and s.count(".") == 3
    if kind == "card":
        return 14 <= len(digits) <= 19 and luhn(digits)
    return 10 <= len(digits) <= 15 and NUMBER.fullmatch(s) is not None and any(c in "(+/.- " for c in s) and not (len(digits) == 13 and digits.startswith("97"))


def model_spans(text: str, tags: np.ndarray) -> list[Span]:
    """Spans of the tags, stretched and checked; of two that then overlap the first stays."""
    out, reach = [], 0
    lit = np.flatnonzero(tags)
    if not len(lit):
        return out
    begins = (np.diff(lit, prepend=-2) > 1) | (tags[lit] % 2 == 1)
    begins |= np.concatenate([[False], (tags[lit][1:] - 1) // 2 != (tags[lit][:-1] - 1) // 2])
    firsts = np.flatnonzero(begins)
    for x, y in zip(firsts, np.append(firsts[1:], len(lit)), strict=True):
        kind = BASE[(tags[lit[x]] - 1) // 2]
        a, b = stretched(text, int(lit[x]), int(lit[y - 1]) + 1, kind)
        if a >= reach and plausible(kind, text[a:b]):
            out.append((a, b, f"lstm_{kind}"))
            reach = b
    return out


def trained(texts: list[str], width: int = 64) -> Tagger:
    """A tagger fitted on labelled windows of some texts and on generated forms in them."""
    parts = [labelled(texts, width), planted(texts, width)]
    model = Tagger()
    model.fit(*(np.concatenate([p[i] for p in parts]) for i in range(2)))
    return model


def find_pii(docs: DataFrame, sample: int = 2000, excerpt: int = 8192, seed: int = 13, windows: Windows = Windows()) -> DataFrame:
    """(doc_id, found array of (start, end, kind)) for every row; extra spans never overlap base ones.

    The network is trained on the first ``excerpt`` characters of ``sample`` rows with a digit or an @, chosen by a hash of the id, and
    on as many generated forms; every whole text is read. Null counts as empty; spans that start together come in the order of the
    kinds; without any text that holds a digit or an @ the patterns stand alone; an empty table gives no rows. Forms without a
    digit or an @ (an address spelled out) are not sought.
    """
    likely = docs.where(F.col("text").rlike("[0-9@]")).select("doc_id", F.substring("text", 1, excerpt).alias("text"))
    texts = [r["text"] for r in sample_rows(likely, sample, seed)]
    model = trained(texts, windows.width) if texts else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(1).fill_null("").to_pylist()
            tagged = (t for i in range(0, len(texts), 256) for t in tag_texts(model, texts[i : i + 256], windows)) if model else itertools.repeat(None)
            out = []
            for text, tags in zip(texts, tagged, strict=False):
                base = base_spans(text)
                extra = outside(model_spans(text, tags), base) if model else []
                out.append([{"start": a, "end": b, "kind": k} for a, b, k in ordered(base + extra, NAMES)])
            kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("kind", pa.string())]))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, kind)], ["doc_id", "found"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, found array<struct<start:long,end:long,kind:string>>")
