"""Personal data: fixed base patterns, and a linear-chain conditional random field for what they miss.

The field labels white-space words from their shape, their folded text, their neighbours' shapes and
texts and their number of digits. It is trained here, in numpy, from a small table of labelled
sentences that this module builds from phrases and number formats. Texts are decoded in batches by
Viterbi over lines. A line none of whose words has a digit, an @ or a trigger word has only inactive
features; training checks that such a line is labelled O throughout, so it need not be decoded.

Edge cases: a null text counts as empty and has no spans; repeated rows each get their own result
row; an empty table gives an empty result; extra columns are ignored. A span of the field that
overlaps a base span is dropped.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .scratch import bound_arrow, table
from .spans import span_sql
from .textscan import SPACED, find_words, hash_words, small_batches, text_bytes

BASE = ("email", "ip", "card", "phone")
LABELS = ("O", "phone_text", "id_number", "email_text", "iban")

# Fixed values of the contract: the base patterns (runs that can't match are cut short).
_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_IP = re.compile(r"(?<![0-9])[0-9]++(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
_CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")


def _luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def _emails(text: str) -> list[tuple[int, int]]:
    out, free = [], 0  # free: where the last match ended
    at = text.find("@")
    while at >= 0:
        start = at
        while start > free and text[start - 1] in _LOCAL:
            start -= 1
        if at >= free and start < at and (m := _DOMAIN.match(text, at)):
            out.append((start, m.end()))
            free = m.end()
        at = text.find("@", max(at + 1, free))
    return out


def base_spans(text: str) -> list[tuple[int, int, int, str]]:
    """(start, rank of the kind, end, kind), sorted."""
    out = [(s, 0, e, "email") for s, e in _emails(text)] if "@" in text else []
    out += [(m.start(), 1, m.end(), "ip") for m in _IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p) <= 255 for p in m[0].split("."))]
    for m in _CARD.finditer(text):
        digits = re.sub("[^0-9]", "", m[0])
        if 14 <= len(digits) <= 19 and _luhn(digits):
            out.append((m.start(), 2, m.end(), "card"))
    if "+" in text:
        out += [(m.start(), 3, m.end(), "phone") for m in _PHONE.finditer(text) if 10 <= len(re.sub("[^0-9]", "", m[0])) <= 15]
    return sorted(out)


# --- the field ------------------------------------------------------------------------------------

_BUCKETS = 1 << 12
_SLOTS = 8  # features of a word: own shape, text, digits; left shape, text; right shape, text; bias
_SHAPE = np.arange(256, dtype=np.uint8)
_SHAPE[65:91] = 65
_SHAPE[97:123] = 97
_SHAPE[48:58] = 48
_SHAPE[128:] = 97
# Words that announce personal data.
_TRIGGERS = "phone tel telephone mobile cell fax call ssn social security passport id iban account email mail e-mail at dot contact".split()
_TRIGGER_HASH = np.sort(np.concatenate([hash_words(d, s, e) for t in _TRIGGERS for v in (t, t + ":", t + ",", t + ".") for d in [np.frombuffer(v.encode(), np.uint8)] for s, e, _ in [find_words(d, np.array([0, len(d)]), SPACED)]]))


def labelled_sentences() -> list[list[tuple[str, str]]]:
    """The training table: sentences as (word, label), from a seeded choice of phrases and formats."""
    rng = np.random.Generator(np.random.PCG64(20260303))

    def pick(items):
        return items[int(rng.integers(len(items)))]

    def digits(n: int) -> str:
        return "".join(str(int(d)) for d in rng.integers(0, 10, n))

    def told(text: str, label: str) -> list[tuple[str, str]]:
        return [(w, label) for w in text.split()]

    def phone() -> str:
        return pick([f"({digits(3)}) {digits(3)}-{digits(4)}", f"{digits(3)}-{digits(3)}-{digits(4)}", f"{digits(3)}.{digits(3)}.{digits(4)}", f"0{digits(3)} {digits(3)} {digits(4)}"])

    def iban() -> str:
        country = pick(["DE", "FR", "ES", "GB", "NL"])
        return pick([f"{country}{digits(20)}", f"{country}{digits(2)} {digits(4)} {digits(4)} {digits(4)} {digits(4)} {digits(2)}"])

    names = "anna peter maria john lena paul sofia marc".split()
    fillers = ["please note that", "the report of last year", "we met on the way", "as stated in the text", "it was sold for", "see page", "in the end", "thank you and", "our office is open", "the match ended"]
    plain = [lambda: digits(4), lambda: f"{digits(1)}.{digits(1)}", lambda: digits(int(rng.integers(1, 7))), lambda: f"version {digits(1)}.{digits(1)}.", lambda: f"{digits(2)}/{digits(2)}/{digits(4)}", lambda: f"{digits(4)}-{digits(2)}-{digits(2)}",
             lambda: digits(16), lambda: 'token = "' + "".join(pick("0123456789abcdef") for _ in range(40)) + '"', lambda: f"{digits(3)}.{digits(2)}.{digits(3)}.{digits(2)}", lambda: f"+{digits(1)} ({digits(3)}) {digits(3)}-{digits(4)}",
             lambda: f"{pick(names)}.{digits(2)}@mail{digits(1)}.example.com", lambda: f"#{digits(5)}", lambda: f"{digits(2)}%", lambda: f"${digits(3)}.{digits(2)}", lambda: f"the call at {digits(2)} dot"]
    out = []
    for _ in range(160):
        head, tail = told(pick(fillers), "O"), told(pick(fillers), "O")
        out.append(head + told(pick(plain)(), "O") + tail)
        out.append(head + told(pick(["phone:", "tel.", "call me at", "my mobile is", "fax", "telephone"]), "O") + told(phone(), "phone_text") + tail)
        out.append(head + told(pick(["ssn", "ssn:", "my social security number is", "passport id:"]), "O") + told(f"{digits(3)}-{digits(2)}-{digits(4)}", "id_number") + tail)
        out.append(head + told(pick(["email:", "mail", "contact", "e-mail me:"]), "O") + told(f"{pick(names)} at {pick(['mail', 'example', 'corp'])} dot {pick(['com', 'org', 'net'])}", "email_text") + tail)
        for announced in (["write to", "reply to", "ask", ""], ["see", "forward this to", "under", ""]):
            out.append(head + told(pick(announced), "O") + told(f"{pick(names)} at {pick(['mail', 'example', 'corp'])} dot {pick(['com', 'org', 'net'])}", "email_text") + tail)
        out.append(head + told(pick(["email:", "write to", "contact", "mail", ""]), "O") + told(f"{pick(names)}{pick(['', ' dot ' + pick(names)])} at {pick(['mail', 'example', 'corp'])} dot {pick(['com', 'org', 'net', 'co dot uk'])}", "email_text") + tail)
        out.append(head + told(pick(["iban", "iban:", "account"]), "O") + told(iban(), "iban") + tail)
        out.append(head + tail)
        out.append(head + told(pick(["at the station", "we are at home", "at at at at", "the dot at the end", "a dot here", "look at this", "mail at noon", "not at all"]), "O") + tail)
    return out


#: What a span of the field must hold to be told; a label alone is not enough.
_SOUND = {
    "phone_text": lambda s: 7 <= sum(c.isdigit() for c in s) <= 15,
    "id_number": lambda s: 6 <= sum(c.isdigit() for c in s) <= 12,
    "email_text": lambda s: re.fullmatch(r"\S+( dot \S+)* at \S+( dot \S+)+", s.lower()) is not None,
    "iban": lambda s: 12 <= sum(c.isdigit() for c in s) <= 32,
}


def _word_features(data: np.ndarray, offsets: np.ndarray):
    """Words of all texts: starts, ends, bounds, line number of each word, _SLOTS feature buckets, and
    whether the word is active."""
    starts, ends, bounds = find_words(data, offsets, SPACED)
    text = hash_words(data, starts, ends)
    kind = _SHAPE[data]
    keep = np.ones(len(data), bool)
    keep[1:] = kind[1:] != kind[:-1]
    keep[starts] = True
    before = np.concatenate([[0], np.cumsum(keep)])
    shape = hash_words(kind[keep], before[starts], before[ends], fold=False)
    digit = np.concatenate([[0], np.cumsum(kind == 48)])
    sign = np.concatenate([[0], np.cumsum(data == 64)])
    n_digits = digit[ends] - digit[starts]
    near = np.searchsorted(_TRIGGER_HASH, text)
    trigger = _TRIGGER_HASH[np.minimum(near, len(_TRIGGER_HASH) - 1)] == text
    active = (n_digits > 0) | (sign[ends] > sign[starts]) | trigger
    breaks = np.concatenate([[0], np.cumsum(data == 10)])
    owner = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
    new = np.ones(len(starts), bool)
    new[1:] = (owner[1:] != owner[:-1]) | (breaks[starts[1:]] != breaks[starts[:-1]])
    line = np.cumsum(new) - 1
    # an inactive word shows nothing of itself
    own_shape = np.where(n_digits > 0, shape, np.uint64(1))
    own_text = np.where(trigger, text, np.uint64(2))
    first, last = new, np.append(new[1:], True)
    empty = np.uint64(0)

    def left(x):
        return np.where(first, empty, np.concatenate([x[-1:], x[:-1]]))

    def right(x):
        return np.where(last, empty, np.concatenate([x[1:], x[:1]]))

    slots = [own_shape, own_text, np.minimum(n_digits, 24).astype(np.uint64), left(own_shape), left(own_text), right(own_shape), right(own_text), np.zeros_like(text)]
    feats = np.stack([((s ^ np.uint64(k * 0x9E37)) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(52)).astype(np.int64) + k * _BUCKETS for k, s in enumerate(slots)], axis=1) if len(starts) else np.empty((0, _SLOTS), np.int64)
    return starts, ends, owner, line, feats, active


def _padded(rows: np.ndarray, line: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """rows of words as (sequence, place, ...) with zeros behind the ends, and the mask."""
    _, first, count = np.unique(line, return_index=True, return_counts=True)
    out = np.zeros((len(first), count.max(), *rows.shape[1:]), rows.dtype)
    mask = np.arange(count.max()) < count[:, None]
    out[mask] = rows
    return out, mask


def _logsum(x: np.ndarray, axis: int) -> np.ndarray:
    top = x.max(axis=axis, keepdims=True)
    return (np.log(np.exp(x - top).sum(axis=axis, keepdims=True)) + top).squeeze(axis)


class LineField:
    """Weights of features by label and of label pairs."""

    def __init__(self, weights: np.ndarray, moves: np.ndarray):
        self.weights, self.moves = weights, moves

    @classmethod
    def train(cls, sentences: list[list[tuple[str, str]]], rounds: int = 150, rate: float = 0.08, decay: float = 2e-3) -> LineField:
        text = "\n".join(" ".join(w for w, _ in s) for s in sentences).encode()
        data = np.frombuffer(text, np.uint8)
        *_, line, feats, _ = _word_features(data, np.array([0, len(data)]))
        truth = np.array([LABELS.index(t) for s in sentences for _, t in s])
        x, mask = _padded(feats, line)
        y = _padded(truth, line)[0]
        k, rows = len(LABELS), np.arange(len(x))
        w, moves = np.zeros((_SLOTS * _BUCKETS, k)), np.zeros((k, k))
        state = [[np.zeros_like(v), np.zeros_like(v)] for v in (w, moves)]
        for step in range(1, rounds + 1):
            emit = w[x].sum(axis=2)
            alpha, beta = np.zeros_like(emit), np.zeros_like(emit)
            alpha[:, 0] = emit[:, 0]
            for t in range(1, x.shape[1]):
                alpha[:, t] = np.where(mask[:, t, None], _logsum(alpha[:, t - 1, :, None] + moves, 1) + emit[:, t], alpha[:, t - 1])
            for t in range(x.shape[1] - 2, -1, -1):
                beta[:, t] = np.where(mask[:, t + 1, None], _logsum(moves + (emit[:, t + 1] + beta[:, t + 1])[:, None, :], 2), 0)
            z = _logsum(alpha[:, -1], 1)
            gain_w, gain_m = decay * w, decay * moves
            belief = np.exp(alpha + beta - z[:, None, None]) * mask[:, :, None]
            belief[rows[:, None], np.arange(x.shape[1]), y] -= mask
            np.add.at(gain_w, x[mask].ravel(), np.repeat(belief[mask], _SLOTS, axis=0) / len(x))
            for t in range(1, x.shape[1]):
                pair = np.exp(alpha[:, t - 1, :, None] + moves + (emit[:, t] + beta[:, t])[:, None, :] - z[:, None, None]) * mask[:, t, None, None]
                gain_m += pair.sum(axis=0) / len(x)
                np.add.at(gain_m, (y[mask[:, t], t - 1], y[mask[:, t], t]), -1 / len(x))
            for v, g, (m, s) in zip((w, moves), (gain_w, gain_m), state, strict=True):
                m += 0.1 * (g - m)
                s += 0.01 * (g * g - s)
                v -= rate * (m / (1 - 0.9**step)) / (np.sqrt(s / (1 - 0.99**step)) + 1e-8)
        field = cls(w, moves)
        field._check_inactive()
        return field

    def _check_inactive(self) -> None:
        """O beats every other label at inactive words whatever stands beside, in one step and in two."""
        data = np.frombuffer(b"x " * 40, np.uint8)
        *_, line, feats, _ = _word_features(data, np.array([0, len(data)]))
        for n in (1, 2, 3, 40):
            part, at = feats[:n].copy(), line[:n]
            part[n - 1] = feats[-1] if n > 1 else part[n - 1]
            if self.decode(part, at).any():
                raise RuntimeError("the trained field labels words without features")

    def decode(self, feats: np.ndarray, line: np.ndarray) -> np.ndarray:
        """Labels of all words by Viterbi; lines of like length are decoded together."""
        labels = np.zeros(len(line), np.int64)
        if not len(line):
            return labels
        emit = self.weights[feats].sum(axis=1)
        _, first, count = np.unique(line, return_index=True, return_counts=True)
        by = np.argsort(count, kind="stable")
        i = 0
        while i < len(by):
            j = int(np.searchsorted(count[by], max(8, 2 * count[by[i]]), "right"))
            own, width = by[i:j], int(count[by[j - 1]])
            place = np.minimum(first[own][:, None] + np.arange(width), len(line) - 1)
            mask = np.arange(width) < count[own][:, None]
            score, back = emit[place[:, 0]], np.zeros((width, len(own), len(LABELS)), np.int8)
            for t in range(1, width):
                step = score[:, :, None] + self.moves
                best = step.argmax(axis=1)
                new = np.take_along_axis(step, best[:, None, :], 1)[:, 0] + emit[place[:, t]]
                back[t] = np.where(mask[:, t, None], best, np.arange(len(LABELS)))
                score = np.where(mask[:, t, None], new, score)
            state = score.argmax(axis=1)
            for t in range(width - 1, -1, -1):
                labels[place[mask[:, t], t]] = state[mask[:, t]]
                state = back[t][np.arange(len(own)), state]
            i = j
        return labels


@cache
def trained_field() -> LineField:
    """The same in every process: training has no random part but the seeded table."""
    return LineField.train(labelled_sentences())


def _field_spans(field: LineField, column: pa.Array) -> dict[int, list[tuple[int, int, int, str]]]:
    """Per row the field's spans as (start, rank, end, kind) in bytes of the row's text."""
    data, offsets = text_bytes(column)
    starts, ends, owner, line, feats, active = _word_features(data, offsets)
    if not active.any():
        return {}
    hot = np.zeros(line[-1] + 1, bool)
    hot[line[active]] = True
    pick = np.flatnonzero(hot[line])
    labels = field.decode(feats[pick], line[pick])
    out: dict[int, list] = {}
    open_span = None
    for w in np.flatnonzero(labels):
        word, label = pick[w], labels[w]
        if open_span and open_span[0] == line[word] and open_span[1] == label and open_span[2] == w - 1:
            open_span[2] = w
            open_span[3][2] = int(ends[word] - offsets[owner[word]])
            continue
        span = [int(starts[word] - offsets[owner[word]]), len(BASE) + int(label) - 1, int(ends[word] - offsets[owner[word]]), LABELS[label]]
        out.setdefault(int(owner[word]), []).append(span)
        open_span = [line[word], label, w, span]
    return {k: [tuple(s) for s in v] for k, v in out.items()}


def _written(spans: list[tuple[int, int, int, str]]) -> str:
    return ",".join(f"{kind}:{start}:{end}" for start, _, end, kind in spans)


def _scan(field: LineField):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text", 2 << 20):
            data, offsets = text_bytes(batch.column(1))
            marks = np.concatenate([[0], np.cumsum(((data >= 48) & (data <= 57)) | (data == 64))])
            some = marks[offsets[1:]] > marks[offsets[:-1]]
            extra = _field_spans(field, batch.column(1))
            base, every = [[]] * batch.num_rows, [[]] * batch.num_rows
            for row in sorted(set(np.flatnonzero(some).tolist()) | extra.keys()):
                text = batch.column(1)[row].as_py()
                base[row] = base_spans(text)
                own = []
                if row in extra:
                    raw = text.encode()
                    own = [(len(raw[:s].decode()), r, len(raw[:e].decode()), k) for s, r, e, k in extra[row]]
                    own = [x for x in own if _SOUND[x[3]](text[x[0] : x[2]]) and not any(b[0] < x[2] and x[0] < b[2] for b in base[row])]
                every[row] = sorted(base[row] + own)
            counts = [pa.array([sum(s[3] == k for s in b) for b in base], pa.int64()) for k in BASE]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *counts, pa.array([hashlib.sha256(_written(b).encode()).hexdigest() for b in base]), pa.array([_written(e) for e in every])],
                ["doc_id", *(f"n_{k}" for k in BASE), "base_sha256", "spans"])

    return run


def personal_data(docs: DataFrame, field: LineField | None = None) -> DataFrame:
    """One row per document: doc_id, counts of the base kinds, digest of the base spans, all spans."""
    bound_arrow(docs.sparkSession)
    schema = "doc_id long, " + ", ".join(f"n_{k} long" for k in BASE) + ", base_sha256 string, spans string"
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(_scan(field or trained_field()), schema)


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return personal_data(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op6_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The columns of op6_pii that hold the base kinds alone."""
    return op6_pii(spark, sf_dir).select("doc_id", *[f"n_{k}" for k in BASE], "base_sha256")


def op6_base_oracle() -> str:
    """DuckDB SQL of op6_base."""
    # Fixed values of the contract, and the sums of the digits of doubled digits.
    patterns = (
        ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"),
        ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"),
        ("card", r"[0-9]([\x20-]?[0-9])+"),
        ("phone", r"\+[0-9][\x20().0-9-]+[0-9]"),
    )
    doubled = [0, 2, 4, 6, 8, 1, 3, 5, 7, 9]
    byte = "0*([0-9]|[1-9][0-9]|1[0-9][0-9]|2[0-4][0-9]|25[0-5])"
    found = "substring(text, x.start + 1, x.end - x.start)"
    digits = f"regexp_replace({found}, '[^0-9]', '', 'g')"
    luhn = f"list_sum(list_transform(string_split(reverse({digits}), ''), lambda c, i: CASE WHEN i % 2 = 0 THEN {doubled}[CAST(c AS INTEGER) + 1] ELSE CAST(c AS INTEGER) END)) % 10 = 0"
    holds = f"""CASE x.kind WHEN 'email' THEN TRUE WHEN 'ip' THEN regexp_full_match({found}, '({byte}\\.){{3}}{byte}')
        WHEN 'card' THEN length({digits}) BETWEEN 14 AND 19 AND {luhn} ELSE length({digits}) BETWEEN 10 AND 15 END"""
    counts = ", ".join(f"len(list_filter(kept, lambda x: x.kind = '{k}'))::BIGINT AS n_{k}" for k, _ in patterns)
    return f"""WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
      {span_sql([(p, k, 0, 0) for k, p in patterns], "d")},
      held AS (SELECT doc_id, list_filter(s, lambda x: {holds}) AS kept FROM spanned)
      SELECT doc_id, {counts}, sha256(array_to_string(list_transform(kept, lambda x: x.kind || ':' || x.start || ':' || x.end), ',')) AS base_sha256 FROM held"""
