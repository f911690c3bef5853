"""Personal data: fixed patterns, and a linear-chain conditional random field over word shapes for what they miss."""

from __future__ import annotations

import hashlib
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import shared

KINDS = ("email", "ip", "card", "phone")
LABELS = ("other", *KINDS)
BLOCK = 128  # words decoded as one sequence; a line that is longer goes on in a new one

# --- fixed patterns -------------------------------------------------------------------------------------------------------

_LOCAL = np.zeros(256, bool)
_LOCAL[[*range(48, 58), *range(65, 91), *range(97, 123), *b"._%+-"]] = True
_AT = re.compile(rb"@")
_DOMAIN = re.compile(rb"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(rb"(?<![0-9])([0-9]++)\.([0-9]++)\.([0-9]++)\.([0-9]++)")
_CARD = re.compile(rb"[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(rb"\+[0-9][ ().0-9-]+[0-9]")
_DIGIT = re.compile(rb"[0-9]")


def luhn(digits: bytes) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = (c - 48) * (1 + k % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def _emails(raw: bytes):
    """Leftmost matches: from each @ the run of local characters to its left, then the domain to its right. Linear in the text."""
    done = 0
    for m in _AT.finditer(raw):
        at = m.start()
        if at < done:
            continue
        a = at
        while a > done and _LOCAL[raw[a - 1]]:
            a -= 1
        if a < at and (d := _DOMAIN.match(raw, at + 1)):
            done = d.end()
            yield a, done
        else:
            done = max(done, a)


def base_spans(raw: bytes) -> list[tuple[int, int, int]]:
    """(start byte, kind, end byte) of the fixed patterns in a text."""
    out = [(a, 0, b) for a, b in _emails(raw)] if b"@" in raw else []
    if not _DIGIT.search(raw):
        return out
    for m in _IP.finditer(raw):
        if all(len(g.lstrip(b"0")) <= 3 and int(g.lstrip(b"0") or b"0") <= 255 for g in m.groups()):
            out.append((m.start(), 1, m.end()))
    for m in _CARD.finditer(raw):
        digits = m.group().replace(b" ", b"").replace(b"-", b"")
        if 12 <= len(digits) <= 19 and luhn(digits):
            out.append((m.start(), 2, m.end()))
    if b"+" in raw:
        for m in _PHONE.finditer(raw):
            if 9 <= len(re.sub(rb"[^0-9]", b"", m.group())) <= 15:
                out.append((m.start(), 3, m.end()))
    return sorted(out)


# --- word shapes ----------------------------------------------------------------------------------------------------------

_KEYWORDS = ("at", "dot", "phone", "tel", "call", "mobile", "email", "mail", "card", "visa", "server", "host", "ip", "fax", "contact", "(at)", "(dot)", "[at]", "[dot]")
_EDGE = b".,;:!?\"'"
_MARKED = np.zeros(256, bool)
_MARKED[[*range(48, 58), *b"@+()[]"]] = True
_HASHES = {int(h): k for h, k in zip(shared.hash_words([w.encode() for w in _KEYWORDS]), _KEYWORDS, strict=True)}
_SORTED = np.array(sorted(_HASHES), np.uint64)


def shape(word: bytes) -> str:
    """Letters become a or A, runs of letters one sign; digits become 9 with the length of their run, up to 5."""
    core = word.strip(_EDGE)
    text = re.sub(rb"[A-Z]+", b"A", core)
    text = re.sub(rb"[a-z\x80-\xff]+", b"a", text).decode("ascii", "replace")
    text = re.sub(r"(?:Aa|aA)+[Aa]?|a+|A+", "a", text)
    return re.sub(r"[0-9]+", lambda m: "9" * min(5, len(m.group())), text)[:40]


def features(word: bytes) -> list[str]:
    s = shape(word)
    n = sum(48 <= c <= 57 for c in word)
    got = [f"shape={s}", f"digits={min(n, 20)}", f"parts={min(4, s.count('.'))}{'9' in s}", f"start={s[:1]}", f"at={'@' in s}", f"plus={s[:1] == '+'}", f"edge={word[-1:] in (b'.', b',')}"]
    if n and re.fullmatch(r"[9(). +-]+", s):
        got.append(f"numeric={min(n, 20)}")
    low = word.strip(_EDGE).decode("utf-8", "replace").lower()
    if low in _KEYWORDS:
        got.append(f"word={low}")
    return got


def coarse(word: bytes) -> str:
    """What a neighbour sees of a word."""
    low = word.strip(_EDGE).decode("utf-8", "replace").lower()
    if low in _KEYWORDS:
        return low
    s = shape(word)
    return "a" if s in ("a", "") else ("number" if re.fullmatch(r"[9(). +-]+", s) else s[:12])


# --- the labelled table ---------------------------------------------------------------------------------------------------


def labelled_table(size: int = 600, seed: int = 7) -> list[tuple[list[bytes], list[int]]]:
    """The small labelled table: sentences filled from patterns by rule, each word with its label. Numbers that are not
    personal data (prices, dates, long ids, versions, tokens) stand among them as `other`."""
    rng = np.random.default_rng(seed)
    letters = "abcdefghijklmnopqrstuvwxyz"
    word = lambda: "".join(rng.choice(list(letters), rng.integers(2, 9)))
    digits = lambda n: "".join(map(str, rng.integers(0, 10, n)))
    makers = {
        1: [lambda: f"{word()}.{digits(2)}@{word()}.com", lambda: f"{word()} at {word()} dot com", lambda: f"{word()} (at) {word()} (dot) org", lambda: f"{word()} [at] {word()} [dot] net", lambda: f"{word()}@{word()}.{word()}.org"],
        2: [lambda: ".".join(str(x) for x in rng.integers(0, 256, 4))],
        3: [lambda: digits(16), lambda: " ".join(digits(4) for _ in range(4)), lambda: "-".join(digits(4) for _ in range(4))],
        4: [lambda: f"+{digits(1)} ({digits(3)}) {digits(3)}-{digits(4)}", lambda: f"({digits(3)}) {digits(3)}-{digits(4)}", lambda: f"{digits(3)}-{digits(3)}-{digits(4)}", lambda: f"+{digits(2)} {digits(3)} {digits(7)}"],
    }
    others = [lambda: digits(int(rng.integers(1, 9))), lambda: f"{digits(4)}-{digits(2)}-{digits(2)}", lambda: f"{digits(1)}.{digits(2)}", lambda: f"{digits(2)}.{digits(1)}.{digits(1)}", lambda: f"${digits(3)}.{digits(2)}", lambda: f"{word()}{digits(3)}", lambda: digits(24), lambda: f"({word()})", lambda: f"{digits(2)}:{digits(2)}", lambda: f"@{word()}", lambda: f"{word()} at {word()}", lambda: f"{digits(3)} {digits(3)}", lambda: f"({digits(4)})", lambda: f"[{digits(2)}]"]
    leads = {1: ["email", "mail", "contact"], 2: ["server", "host", "ip"], 3: ["card", "visa"], 4: ["phone", "tel", "call", "mobile", "fax"]}
    table = []
    for _ in range(size):
        words, labels = [], []
        for _ in range(int(rng.integers(2, 6))):
            for _ in range(int(rng.integers(1, 5))):
                w = word()
                words.append(w.capitalize() if rng.random() < 0.2 else w)
                labels.append(0)
            kind = int(rng.integers(0, 6))
            if kind in makers:
                if rng.random() < 0.4:
                    words.append(str(rng.choice(leads[kind])))
                    labels.append(0)
                made = makers[kind][int(rng.integers(len(makers[kind])))]().split(" ")
                if rng.random() < 0.2:
                    made[-1] += str(rng.choice([".", ","]))
                words += made
                labels += [kind] * len(made)
            else:
                made = others[int(rng.integers(len(others)))]().split(" ")
                words += made
                labels += [0] * len(made)
        table.append(([w.encode() for w in words], labels))
    return table


# --- the model ------------------------------------------------------------------------------------------------------------


class Tagger:
    """Weights of words' features, of both neighbours' coarse shapes, and of label pairs; trained by gradient ascent on the
    likelihood of the labelled table (forward-backward in numpy), decoded by Viterbi over many sequences side by side."""

    def __init__(self, table, rounds: int = 120, ridge: float = 0.05):
        names: dict[str, int] = {}
        rows = []
        for words, _ in table:
            seen = [coarse(w) for w in words]
            rows.append([self._ids(names, w, seen[i - 1] if i else "", seen[i + 1] if i + 1 < len(words) else "", True) for i, w in enumerate(words)])
        self.names, n, length, count = names, len(table), max(len(r) for r in rows), len(LABELS)
        gold = np.full((n, length), -1)
        for i, (_, labels) in enumerate(table):
            gold[i, : len(labels)] = labels
        live = gold >= 0
        flat = [(i, t, f) for i, r in enumerate(rows) for t, fs in enumerate(r) for f in fs]
        at_i, at_t, at_f = np.array(flat).T
        self.weights, self.pairs = np.zeros((len(names), count)), np.zeros((count, count))
        state = [np.zeros_like(self.weights), np.zeros_like(self.weights), np.zeros_like(self.pairs), np.zeros_like(self.pairs)]
        onehot = np.zeros((n, length, count))
        onehot[live, gold[live]] = 1
        pair_gold = np.einsum("nta,ntb->ab", onehot[:, :-1], onehot[:, 1:])
        for step in range(1, rounds + 1):
            score = np.zeros((n, length, count))
            np.add.at(score, (at_i, at_t), self.weights[at_f])
            alpha, beta = np.zeros_like(score), np.zeros_like(score)
            alpha[:, 0] = score[:, 0]
            for t in range(1, length):
                now = score[:, t] + _lse(alpha[:, t - 1, :, None] + self.pairs, 1)
                alpha[:, t] = np.where(live[:, t, None], now, alpha[:, t - 1])
            for t in range(length - 2, -1, -1):
                now = _lse(self.pairs + (score[:, t + 1] + beta[:, t + 1])[:, None, :], 2)
                beta[:, t] = np.where(live[:, t + 1, None], now, 0)
            z = _lse(alpha[:, -1], 1)
            p = np.exp(alpha + beta - z[:, None, None]) * live[:, :, None]
            both = np.exp(alpha[:, :-1, :, None] + self.pairs + (score + beta)[:, 1:, None, :] - z[:, None, None, None]) * live[:, 1:, None, None]
            g = np.zeros_like(self.weights)
            np.add.at(g, at_f, (onehot - p)[at_i, at_t])
            for k, (w, grad) in enumerate(((self.weights, g), (self.pairs, pair_gold - both.sum((0, 1))))):
                grad = (grad - ridge * w) / n
                m, v = state[2 * k], state[2 * k + 1]
                m *= 0.9
                m += 0.1 * grad
                v *= 0.99
                v += 0.01 * grad**2
                w += 0.15 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
        self.cache: dict[bytes, tuple[np.ndarray, int]] = {}
        self.coarse_ids = {c[5:]: k for k, c in enumerate(x for x in names if x.startswith("prev="))}
        self.prev = np.array([self.weights[names["prev=" + c]] for c in self.coarse_ids] + [np.zeros(count)])
        self.next = np.array([self.weights[names["next=" + c]] if "next=" + c in names else np.zeros(count) for c in self.coarse_ids] + [np.zeros(count)])
        self.edge = np.array([self.weights[names["prev="]], self.weights[names["next="]]])

    @staticmethod
    def _ids(names, word, before, after, grow):
        got = [*features(word), f"prev={before}", f"next={after}"]
        return [names.setdefault(f, len(names)) if grow else names[f] for f in got if grow or f in names]

    def own(self, word: bytes) -> tuple[np.ndarray, int]:
        """Score of a word's own features, and its coarse shape's number."""
        hit = self.cache.get(word)
        if hit is None:
            ids = [self.names[f] for f in features(word) if f in self.names]
            hit = (self.weights[ids].sum(0), self.coarse_ids.get(coarse(word), len(self.coarse_ids)))
            if len(self.cache) < 200_000:  # a word outside the cache is only worked out again
                self.cache[word] = hit
        return hit

    def emissions(self, buf, start, end, hashes, doc_line):
        """Scores of all words of a slice. Words without digits or signs that matter share the row of a plain word."""
        n, count = len(start), len(LABELS)
        score = np.empty((n, count))
        plain, kind = self.own(b"word")
        score[:], coarse_of = plain, np.full(n, kind)
        marks = np.concatenate([[0], np.cumsum(_MARKED[buf])])
        odd = marks[end] > marks[start]
        last = buf[end - 1] if n else np.zeros(0, np.uint8)
        edged = ~odd & ((last == 46) | (last == 44))
        score[edged], coarse_of[edged] = self.own(b"word.")
        core = shared.word_hashes(buf, start, np.where(edged, end - 1, end))
        key = _SORTED[np.minimum(np.searchsorted(_SORTED, core), len(_SORTED) - 1)] == core
        raw = buf.tobytes()
        for i in np.flatnonzero(odd | key).tolist():
            score[i], coarse_of[i] = self.own(raw[start[i] : end[i]] if end[i] - start[i] <= 64 else raw[start[i] : start[i] + 64])
        same = doc_line[1:] == doc_line[:-1]
        if n:
            before, after = np.empty((n, count)), np.empty((n, count))
            before[0], after[-1] = self.edge
            before[1:] = np.where(same[:, None], self.prev[coarse_of[:-1]], self.edge[0])
            after[:-1] = np.where(same[:, None], self.next[coarse_of[1:]], self.edge[1])
            score += before + after
        return score, odd | key

    def decode(self, score: np.ndarray, first: np.ndarray, length: np.ndarray) -> np.ndarray:
        """Best labels of sequences that lie one after another in `score`."""
        out = np.zeros(len(score), np.int8)
        order = np.argsort(-length, kind="stable")
        first, length = first[order], length[order]
        if not len(first) or not length[0]:
            return out
        wide = np.searchsorted(-length, -np.arange(length[0]), "left")
        back = []
        best = score[first]
        final = best.copy()
        for t in range(1, int(length[0])):
            w = int(wide[t])
            options = best[:w, :, None] + self.pairs
            back.append(options.argmax(1).astype(np.int8))
            best = np.take_along_axis(options, back[-1][:, None, :].astype(np.int64), 1)[:, 0] + score[first[:w] + t]
            final[:w] = best
        label = final.argmax(1).astype(np.int8)
        for t in range(int(length[0]) - 1, -1, -1):
            w = int(wide[t])
            out[first[:w] + t] = label[:w]
            if t:
                label[:w] = back[t - 1][np.arange(w), label[:w]]
        return out


def _lse(x, axis):
    top = x.max(axis, keepdims=True)
    return (np.log(np.exp(x - top).sum(axis, keepdims=True)) + top).squeeze(axis)


@lru_cache(maxsize=2)
def tagger(size: int = 600, rounds: int = 120) -> Tagger:
    return Tagger(labelled_table(size), rounds)


_OBFUSCATED = re.compile(rb"[A-Za-z0-9._%+-]+ [\[(]?at[\])]? [A-Za-z0-9-]+(?: [\[(]?dot[\])]? [A-Za-z0-9-]+)+", re.I)


def _plausible(kind: int, raw: bytes) -> bool:
    """Whether a run of words with one label can be what the label says."""
    digits = re.sub(rb"[^0-9]", b"", raw)
    if kind == 1:
        return bool(_OBFUSCATED.fullmatch(raw))
    if kind == 2:
        parts = raw.split(b".")
        return len(parts) == 4 and all(p.isdigit() and len(p) < 4 and int(p) < 256 for p in parts)
    if kind == 3:
        return 12 <= len(digits) <= 19 and luhn(digits)
    return bool(re.fullmatch(rb"\+?[0-9(][0-9 ().-]*", raw)) and 10 <= len(digits) <= 15


def find(text: pa.Array, model: Tagger):
    """For each text: spans by the patterns and all spans, as (start, kind, end) in code points."""
    for a, b, buf, offs in shared.slices(text):
        points = np.concatenate([[0], np.cumsum((buf & 0xC0) != 0x80)])
        start, end = shared.word_spans(buf, offs, shared.SPACED)
        doc = np.searchsorted(offs, start, "right") - 1
        lines = np.concatenate([[0], np.cumsum(buf == 10)])
        line = lines[start] * (b - a + 1) + doc if len(start) else start
        fresh = np.flatnonzero(np.concatenate([[True], line[1:] != line[:-1]])) if len(start) else start
        size = np.diff(np.append(fresh, len(start)))
        cut = -(-size // BLOCK)
        within = np.arange(cut.sum()) - np.repeat(np.cumsum(cut) - cut, cut)
        first = np.repeat(fresh, cut) + within * BLOCK
        length = np.minimum(BLOCK, np.repeat(size, cut) - within * BLOCK)
        score, marked = model.emissions(buf, start, end, None, line)
        label = model.decode(score, first, length)
        run_first = np.flatnonzero((label > 0) & np.concatenate([[True], (label[1:] != label[:-1]) | (line[1:] != line[:-1])])) if len(label) else start
        more: dict[int, list] = {}
        raw = buf.tobytes()
        for i in run_first.tolist():
            j = i
            while j + 1 < len(label) and label[j + 1] == label[i] and line[j + 1] == line[i]:
                j += 1
            x, y = int(start[i]), int(end[j])
            while y > x and raw[y - 1] in _EDGE:
                y -= 1
            if _plausible(int(label[i]), raw[x:y]):
                more.setdefault(int(doc[i]), []).append((x, int(label[i]) - 1, y))
        signs = np.add.reduceat(np.append(_MARKED[buf], False).astype(np.int32), np.minimum(offs[:-1], len(buf))) if b > a else []
        for d in range(b - a):
            x, y = int(offs[d]), int(offs[d + 1])
            base = [(s + x, k, e + x) for s, k, e in base_spans(raw[x:y])] if y > x and signs[d] else []
            taken = list(base)
            for s in more.get(d, ()):
                if all(s[2] <= t[0] or s[0] >= t[2] for t in base):
                    taken.append(s)
            zero = int(points[x])
            yield tuple([(int(points[s]) - zero, k, int(points[e]) - zero) for s, k, e in sorted(part)] for part in (base, taken))


def joined(spans) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


def detect(docs: DataFrame, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Add n_email, n_ip, n_card, n_phone (by the fixed patterns), base (their spans) and spans (all) to the columns in `keep`.

    Spans are written kind:start:end in code points, end exclusive, by start and then by kind, joined by commas. What the
    random field adds never overlaps a pattern's span and passes the kind's own test (digits, Luhn, parts). Null and empty
    texts have none. Repeated rows get equal answers.
    """
    keep = shared.kept(docs, keep, (*(f"n_{k}" for k in KINDS), "base", "spans"))
    rows = docs.select(*keep, F.col(text_col).alias("_pairdict_text"))
    held = docs.sparkSession.sparkContext.broadcast(tagger())  # of fixed size: it knows the labelled table alone

    def run(batches):
        for batch in batches:
            got = list(find(batch.column(batch.num_columns - 1), held.value))
            counts = [pa.array([sum(s[1] == k for s in g[0]) for g in got], pa.int64()) for k in range(len(KINDS))]
            text = [pa.array([joined(g[i]) for g in got], pa.string()) for i in (0, 1)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], *counts, *text], [*keep, *(f"n_{k}" for k in KINDS), "base", "spans"])

    fields = "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in rows.schema.fields[:-1])
    return rows.mapInArrow(run, fields + ", ".join(f"n_{k} long" for k in KINDS) + ", base string, spans string")


def digest(base: str) -> str:
    return hashlib.sha256(base.encode()).hexdigest()


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = detect(shared.documents(spark, sf_dir), keep=["doc_id"])
    return out.select("doc_id", *(f"n_{k}" for k in KINDS), F.sha2(F.col("base").cast("binary"), 256).alias("base_sha256"), "spans")
