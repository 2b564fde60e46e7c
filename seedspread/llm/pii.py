"""Personal data: exact patterns with checks, plus spans decoded by a character BiLSTM-CRF.

The patterns give the base spans. The tagger is trained on the base spans of a bounded sample of the corpus
(``TRAIN_DOCS`` texts), on the keys and tokens beside them (kind ``secret``, which has no base pattern), and on
altered copies of both that the patterns do not cover (a phone number with 00 for +, a spelled-out at sign,
separators inside an address, other secrets); it adds spans that overlap no base span.

Overlapping windows lie on a fixed grid over the whole text. Each window is decoded on its own, and a
character's tag comes from the window in whose interior it lies deepest, so spans that cross window borders
come out once. A span counts only if it is ``plausible``, so it holds a digit, an at sign or a spelled-out one
(``TRIGGER``): the windows that judge those are decoded, then their neighbours for as long as a tagged run
reaches the border. The result is that of decoding every window of the text.

Training takes a seeded choice of the windows of all sampled texts: up to 1.5 ``TRAIN_DOCS`` with a mark, and as
many without (64 at least).

Cases: null and empty texts have no spans; repeated rows give repeated results; offsets count code points.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seedspread.llm.tagger import Tagger, symbols

KINDS = ("email", "ip", "card", "phone")
#: Kinds that no pattern gives and the tagger alone finds.
TAGGED = ("secret",)
ALL = KINDS + TAGGED
TRAIN_DOCS, TRAIN_CHARS, WIDTH, STRIDE = 600, 20_000, 96, 48

# The base patterns. Their first character class is guarded against being entered in mid-run, which changes no match and keeps the scan linear.
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
#: Where alone what ``plausible`` accepts can stand.
TRIGGER = re.compile(r"[0-9@]| at(?= )")


#: Labels of the tagger's own kind for training: long unbroken runs that mix letters and several digits, as keys and tokens do.
SECRET = re.compile(r"(?<![A-Za-z0-9+/_=-])(?=[A-Za-z+/_-]*[0-9][A-Za-z+/_-]*[0-9][A-Za-z+/_-]*[0-9])(?=[0-9+/_-]*[A-Za-z][0-9+/_-]*[A-Za-z])[A-Za-z0-9+/_-]{20,80}(?![A-Za-z0-9+/_@.-])")


def training_spans(text: str) -> list[tuple[int, int, int]]:
    """The base spans and the secrets beside them."""
    base = base_spans(text)
    return base + [(len(KINDS), *m.span()) for m in SECRET.finditer(text) if all(m.end() <= s or m.start() >= e for _, s, e in base)]


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = int(c) * (1 + k % 2)
        total += d - 9 if d > 9 else d
    return total % 10 == 0


def _digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def _emails(text: str) -> Iterator[tuple[int, int]]:
    done = 0
    at = text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in LOCAL:
            start -= 1
        found = DOMAIN.match(text, at) if start < at else None
        if found:
            yield start, found.end()
            done = found.end()
        at = text.find("@", max(at + 1, done))


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(kind, start, end) of every base span, by kind and start."""
    out = [(0, s, e) for s, e in _emails(text)]
    for m in IP.finditer(text):
        if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m[0].split(".")):
            out.append((1, *m.span()))
    for m in CARD.finditer(text):
        if m.end() - m.start() <= 2 * 19 and 16 <= len(d := _digits(m[0])) <= 19 and luhn(d):
            out.append((2, *m.span()))
    for m in PHONE.finditer(text):
        if 8 <= len(_digits(m[0])) <= 15:
            out.append((3, *m.span()))
    return out


def owner(at: int, n: int) -> int:
    """The grid window, of a text of ``n`` characters, in which the character lies deepest."""
    last = max(0, -((WIDTH - n) // STRIDE))
    return min(max(0, (at - (WIDTH - STRIDE) // 2) // STRIDE), last)


def window(k: int, n: int) -> tuple[int, int]:
    return k * STRIDE, min(k * STRIDE + WIDTH, n)


def windows(text: str) -> list[tuple[int, int]]:
    """The (start, end) of the grid windows that judge a trigger."""
    n = len(text)
    return [window(k, n) for k in sorted({owner(m.start(), n) for m in TRIGGER.finditer(text)})]


def encode_windows(text: str, spans: list[tuple[int, int]]) -> np.ndarray:
    out = np.zeros((len(spans), WIDTH), np.int64)
    for k, (lo, hi) in enumerate(spans):
        out[k, : hi - lo] = symbols(np.frombuffer(text[lo:hi].encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64))
    return out


def tag_rows(spans: list[tuple[int, int]], marks: list[tuple[int, int, int]]) -> np.ndarray:
    """Begin/inside tags (1 + 2 kind, 2 + 2 kind) of marks inside each window."""
    out = np.zeros((len(spans), WIDTH), np.int64)
    for k, (lo, hi) in enumerate(spans):
        for kind, s, e in marks:
            if s < hi and e > lo:
                out[k, max(s, lo) - lo : min(e, hi) - lo] = 2 + 2 * kind
                if s >= lo:
                    out[k, s - lo] = 1 + 2 * kind
    return out


def reconcile(spans: list[tuple[int, int]], tags: np.ndarray) -> list[tuple[int, int, int]]:
    """(kind, start, end) over the text from the windows' tags, each character judged by its deepest window."""
    best: dict[int, tuple[int, int]] = {}
    for k, (lo, hi) in enumerate(spans):
        for at in range(lo, hi):
            depth = min(at - lo, hi - 1 - at)
            if at not in best or depth > best[at][0]:
                best[at] = (depth, int(tags[k, at - lo]))
    out: list[list[int]] = []
    last = -2
    for at in sorted(best):
        tag = best[at][1]
        if tag:
            kind = (tag - 1) // 2
            if out and at == last + 1 and out[-1][0] == kind and (tag % 2 == 0):
                out[-1][2] = at + 1
            else:
                out.append([kind, at, at + 1])
            last = at
    return [tuple(x) for x in out]


def tagged_spans(texts: list[str], decode: Callable[[np.ndarray], np.ndarray]) -> list[list[tuple[int, int, int]]]:
    """The plausible (kind, start, end) of each text, as if every window of it were decoded."""
    held: list[dict[int, np.ndarray]] = [{} for _ in texts]
    todo = [(i, lo // STRIDE) for i, text in enumerate(texts) for lo, _ in windows(text)]
    while todo:
        for at in range(0, len(todo), 512):
            part = todo[at : at + 512]
            tags = decode(np.concatenate([encode_windows(texts[i], [window(k, len(texts[i]))]) for i, k in part]))
            for (i, k), row in zip(part, tags.astype(np.int8), strict=True):
                held[i][k] = row
        more = set()
        for i, k in todo:
            n, last = len(texts[i]), owner(len(texts[i]) - 1, len(texts[i]))
            lo, hi = window(k, n)
            first, end = lo + (WIDTH - STRIDE) // 2 if k else 0, lo + (WIDTH + STRIDE) // 2 if k < last else hi
            if k and k - 1 not in held[i] and held[i][k][first - lo]:
                more.add((i, k - 1))
            if k < last and k + 1 not in held[i] and held[i][k][end - 1 - lo]:
                more.add((i, k + 1))
        todo = sorted(more)
    out = []
    for text, rows in zip(texts, held, strict=True):
        keys = sorted(rows)
        found = reconcile([window(k, len(text)) for k in keys], np.array([rows[k] for k in keys]))
        out.append([f for f in found if plausible(f[0], text[f[1] : f[2]])])
    return out


def plausible(kind: int, s: str) -> bool:
    """What any span of the kind must hold, however it is written."""
    n = len(_digits(s))
    return (kind == 0 and ("@" in s or " at " in s) and len(s) >= 6) or (kind == 1 and 4 <= n <= 12 and len(s) >= 7) or (kind == 2 and 13 <= n <= 19) or (kind == 3 and 8 <= n <= 15) or (kind == 4 and n >= 3 and len(s) >= 16 and not any(c in s for c in " \n\t"))


def _altered(text: str, marks: list[tuple[int, int, int]], rng) -> tuple[str, list[tuple[int, int, int]]]:
    """The text with its spans rewritten in forms that the patterns miss, and the marks of the result."""
    out, done, moved = [], 0, []
    size = 0
    for kind, s, e in sorted(marks, key=lambda m: m[1]):
        if s < done:
            continue
        span = text[s:e]
        if kind == 0:
            span = span.replace("@", " at ", 1)
        elif kind == 3:
            span = "00" + span[1:] if rng.random() < 0.5 else span[1:].replace(" ", "-")
        elif kind == len(KINDS):
            alphabet = "0123456789abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ"[: int(rng.choice([16, 36, 62]))]
            span = "".join(alphabet[x] for x in rng.integers(0, len(alphabet), int(rng.integers(20, 50))))
        elif kind == 1 and rng.random() < 0.5:
            span = span.replace(".", " . ", 1)
        out += [text[done:s], span]
        size += s - done
        moved.append((kind, size, size + len(span)))
        size += len(span)
        done = e
    return "".join(out) + text[done:], moved


def fit(docs: DataFrame, train_docs: int = TRAIN_DOCS) -> dict | None:
    """Tagger parameters from the base spans of at most ``train_docs`` of the texts that can hold one; None where there are none."""
    has = docs.filter(F.col("text").rlike("[0-9@]") & (F.length("text") <= TRAIN_CHARS))
    # ids first, so that a task sends ids and not texts to be ranked
    order = [F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))), F.col("_th")]
    marked = has.select("doc_id", F.xxhash64("text").alias("_th"), "text")
    picked = marked.select("doc_id", "_th").orderBy(*order).limit(train_docs).select(F.col("doc_id").alias("_id"), F.col("_th").alias("_t"))
    same = F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("_th") == F.col("_t"))
    texts = sorted({r["text"]: None for r in marked.join(F.broadcast(picked), same, "left_semi").select("text").distinct().collect()})
    rng, marked_at, plain_at = np.random.default_rng(5), [], []
    for text in texts:
        marks = training_spans(text)
        versions = [(text, marks)] + ([_altered(text, marks, rng)] if marks else [])
        for body, spans in versions:
            for at in windows(body):
                near = [m for m in spans if m[1] < at[1] and m[2] > at[0]]
                (marked_at if near else plain_at).append((body, at, near))
    if not marked_at:
        return None
    choice = np.random.default_rng(6)
    most = 3 * train_docs // 2
    chosen = [marked_at[k] for k in np.sort(choice.permutation(len(marked_at))[:most])]
    chosen += [plain_at[k] for k in np.sort(choice.permutation(len(plain_at))[: max(64, len(chosen))])]
    x = np.concatenate([encode_windows(body, [at]) for body, at, _ in chosen])
    y = np.concatenate([tag_rows([at], near) for _, at, near in chosen])
    tagger = Tagger(1 + 2 * len(ALL))
    tagger.fit(x, y, epochs=max(4, min(30, 6_000 // len(x))))
    return tagger.p


def render(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{ALL[k]}:{s}:{e}" for k, s, e in sorted(spans))


def _scanned(texts: list[str], tagger: Tagger | None) -> Iterator[tuple[list, list]]:
    """(base spans, further spans of the tagger) of each text, texts of about a megabyte at a time."""

    def close(group):
        near = [k for k, t in enumerate(group) if TRIGGER.search(t)]
        base = {k: base_spans(group[k]) for k in near}
        more: dict[int, list] = {}
        if tagger is not None and near:
            for k, found in zip(near, tagged_spans([group[k] for k in near], lambda x: _decode(tagger, x)), strict=True):
                more[k] = [f for f in found if all(f[2] <= s or f[1] >= e for _, s, e in base[k])]
        return [(base.get(k, []), more.get(k, [])) for k in range(len(group))]

    group, size = [], 0
    for text in texts:
        group.append(text or "")
        size += len(group[-1])
        if size >= 1_000_000:
            yield from close(group)
            group, size = [], 0
    yield from close(group)


def _tagger(parameters: dict | None) -> Tagger | None:
    if parameters is None:
        return None
    tagger = Tagger(1 + 2 * len(ALL))
    tagger.p = parameters
    return tagger


def find(docs: DataFrame, parameters: dict | None) -> DataFrame:
    """``docs(doc_id, text)`` → counts and digest of base spans, all spans with the tagger's, their number and whether there is one."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tagger = _tagger(parameters)
        names = ["doc_id", *(f"n_{k}" for k in KINDS), "base_sha256", "spans", "n_spans", "private"]
        for batch in batches:
            found = list(_scanned(batch.column(1).to_pylist(), tagger))
            counts = [pa.array([sum(s[0] == kind for s in base) for base, _ in found], pa.int64()) for kind in range(4)]
            digests = pa.array([hashlib.sha256(render(base).encode()).hexdigest() for base, _ in found], pa.string())
            total = [len(base) + len(more) for base, more in found]
            rest = [digests, pa.array([render(base + more) for base, more in found], pa.string()), pa.array(total, pa.int64()), pa.array([n > 0 for n in total], pa.bool_())]
            yield pa.RecordBatch.from_arrays([batch.column(0), *counts, *rest], names=names)

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return rows.mapInArrow(run, "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_spans long, private boolean")


def _decode(tagger: Tagger, x: np.ndarray) -> np.ndarray:
    """Tags of the windows, a few hundred at a time so that memory stays small."""
    return np.concatenate([tagger.decode(x[k : k + 512]) for k in range(0, len(x), 512)])


def redact(docs: DataFrame, parameters: dict | None) -> DataFrame:
    """``docs`` with every found span of ``text`` replaced by its kind in brackets, row by row in one pass; other columns stay."""
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tagger = _tagger(parameters)
        for batch in batches:
            texts = batch.column(at).to_pylist()
            out = []
            for text, (base, more) in zip(texts, _scanned(texts, tagger), strict=True):
                for kind, s, e in sorted(base + more, key=lambda x: -x[1]):
                    text = text[:s] + f"[{ALL[kind]}]" + text[e:]
                out.append(text)
            yield batch.set_column(at, batch.schema.field(at), pa.array(out, batch.schema.field(at).type))

    return docs.mapInArrow(run, docs.schema)
