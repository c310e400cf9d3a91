"""Secret scan: base patterns, and a linear-chain conditional random field over tokens.

One pass over the texts finds the base spans (leftmost, not overlapping within a kind) and cuts out every run of words
that a secret may be in, with ``BEFORE`` tokens before it and ``AFTER`` behind. Every token of a word that has a candidate
token may be inside a secret, and only candidates may begin one (a hard constraint of the field). All other tokens are
outside, so the chain falls apart at them, and as features look no further than the cut tokens, decoding the cuts
equals decoding the whole text. Tags are begin, inside and outside; weights are trained on a bounded sample of
cuts, half of them from documents with base spans, tagged by the values in these spans, with the name before the value hidden
in part of the copies so that shape and file features have to speak too; words without a name that look like such values
(characters and length) are left out, as they may be secrets. Viterbi decoding adds the spans that no
base pattern covers.

Defined results: a null or empty text has no spans and the digest of the empty string; texts of any length are read whole;
equal spans cannot occur within a kind; repeated rows are scanned each; without a base span in the table nothing is learned and no
span added; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_schema, checkpoint, chunks, lowest_hashes, text_bytes

#: The base kinds in their order, their patterns and least lengths.
KINDS = ("assign", "access", "hex", "crf")
ASSIGN = re.compile(r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
HEX_LONG = re.compile(rb"[0-9a-f]{24}")
LEAST = {"assign": 6, "access": 20, "hex": 24}
NAMES = re.compile(rb"passw|secret|token|api_?key", re.I)

#: Characters of a token that may carry a secret; any other character but white space is a token of its own.
CORE = r"A-Za-z0-9+/_=-"
TOKEN = re.compile(rf"[{CORE}]+|[^\s{CORE}]")
WORD = re.compile(r"\S+")
#: Places that may belong to a candidate: a digit next to a letter or sign, eight digits, a capital inside a word, a value.
HINT = re.compile(rb"[0-9][A-Za-z+/_=-]|[A-Za-z+/_=-][0-9]|[0-9]{8}|[a-z][A-Z]|[:=]\s*[\"']?\s*[A-Za-z0-9+/_=-]{6}")
LETTER, DIGIT, TURN = re.compile(r"[A-Za-z]"), re.compile(r"[0-9]"), re.compile(r"[a-z][A-Z]")
BEFORE, AFTER = 3, 2
WINDOW = 64
#: Cuts that the field is trained on, and cuts of one document among them.
SAMPLE_CUTS, DOCUMENT_CUTS = 6000, 20
BUCKETS = 1 << 14
TAGS = "BIO"


def base_spans(body: bytes | None) -> list[tuple[str, int, int, int]]:
    """(kind, start, end, start of the value) in code points of the base patterns."""
    if not body:
        return []
    named, access, hexes = NAMES.search(body), b"AKIA" in body, HEX_LONG.search(body)
    if not (named or access or hexes):
        return []
    text, spans = body.decode("utf-8", "replace"), []
    if named:
        spans += [("assign", m.start(), m.end(), m.start(2)) for m in ASSIGN.finditer(text) if len(m[2]) >= LEAST["assign"]]
    if access:
        spans += [("access", m.start(), m.end(), m.start()) for m in ACCESS.finditer(text) if len(m[0]) >= LEAST["access"]]
    if hexes:
        spans += [("hex", m.start(), m.end(), m.start()) for m in HEX.finditer(text) if len(m[0]) >= LEAST["hex"]]
    return spans


def listed(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{s}:{e}" for k, s, e in sorted(spans, key=lambda x: (x[1], KINDS.index(x[0]), x[2])))


def is_candidate(token: str, valued: bool) -> bool:
    """Whether a token may begin a secret; ``valued``: it stands behind a colon or equals sign."""
    n = len(token)
    if n < 6 or not token.isascii():
        return False
    letter, digit = LETTER.search(token), DIGIT.search(token)
    return bool(valued or n >= 8 and digit or n >= 10 and letter and TURN.search(token))


def tokens_of(text: str) -> list[tuple[int, int, str, int]]:
    """(start, end, token, mark); a name glued to its value by '=' is cut off.

    mark 2: may begin a secret, 1: in a word with such a token, so it may go on with one, 0: outside. Words are runs
    without white space.
    """
    out: list[tuple[int, int, str, int]] = []
    word_end, first = -1, 0

    def close():
        if any(t[3] == 2 for t in out[first:]):
            out[first:] = [(s, e, t, m or 1) for s, e, t, m in out[first:]]

    for m in TOKEN.finditer(text):
        s, e = m.span()
        if s != word_end:
            close()
            first = len(out)
        word_end = e
        cut = re.match(r"([A-Za-z_-]+)=+", m[0])
        if cut and cut.end() < e - s:
            out += [(s, s + len(cut[1]), cut[1], 0), (s + len(cut[1]), s + cut.end(), "=", 0)]
            s += cut.end()
        near = [t[2] for t in out[-2:]]
        valued = near[-1:] in ([":"], ["="]) or near[-1:] in (["'"], ['"']) and near[:1] in ([":"], ["="])
        out.append((s, e, text[s:e], 2 if is_candidate(text[s:e], valued) else 0))
    close()
    return out


def tokens_left(text: str, at: int, count: int) -> int:
    """Where the word with the ``count``-th token before ``at``, the start of a word, begins (or the first, if there are fewer)."""
    reach = WINDOW
    while True:
        lo = max(0, at - reach)
        while lo and not text[lo - 1].isspace():  # tokens and names cut off by '=' never reach over white space
            lo -= 1
        tokens = tokens_of(text[lo:at])
        if lo == 0 or len(tokens) >= count:
            at = lo + tokens[-count:][0][0] if tokens else at
            while at > lo and not text[at - 1].isspace():
                at -= 1
            return at
        reach *= 4


def tokens_right(text: str, at: int, count: int) -> int:
    """Where the word with the ``count``-th token from ``at``, the end of a word, ends."""
    reach = WINDOW
    while True:
        hi = min(len(text), at + reach)
        while hi < len(text) and not text[hi].isspace():
            hi += 1
        tokens = tokens_of(text[at:hi])
        if hi == len(text) or len(tokens) >= count:
            at = at + tokens[:count][-1][1] if tokens else at
            while at < hi and not text[at].isspace():
                at += 1
            return at
        reach *= 4


def snippets(body: bytes | None) -> list[tuple[int, int, int, str]]:
    """(start, first, last, text) of each run of words with a candidate: the run is text[first:last], around it its neighbours."""
    if not body or not HINT.search(body):
        return []
    text, runs, seen = body.decode("utf-8", "replace"), [], -1
    plain = text.encode("ascii", "replace") if not text.isascii() else body
    for hint in HINT.finditer(plain):
        at = hint.end() - 1  # a character of the token in question
        if at < seen:
            continue
        lo = at
        while lo and not text[lo - 1].isspace():
            lo -= 1
        hi = WORD.match(text, at).end() if not text[at].isspace() else at
        seen = hi
        context = tokens_left(text, lo, 2)
        if hi > lo and any(t[3] == 2 and t[0] >= lo - context for t in tokens_of(text[context:hi])):
            if runs and not text[runs[-1][1] : lo].strip():
                runs[-1][1] = hi
            else:
                runs.append([lo, hi])
    out = []
    for lo, hi in runs:
        start = tokens_left(text, lo, BEFORE)
        out.append((start, lo - start, hi - start, text[start : tokens_right(text, hi, AFTER)]))
    return out


def marked(snippet: str, first: int, last: int) -> list[tuple[int, int, str, int]]:
    """Tokens of a cut; the ones around its run are outside."""
    return [(s, e, t, m if first <= s < last else 0) for s, e, t, m in tokens_of(snippet)]


def shape(token: str) -> str:
    return re.sub(r"(.)\1+", r"\1", re.sub("[0-9]", "9", re.sub("[a-z]", "a", re.sub("[A-Z]", "A", token[:64]))))[:12]


def charset(token: str) -> str:
    for name, pattern in (("hex", r"[0-9a-f]+"), ("upper", r"[A-Z0-9]+"), ("lower", r"[a-z0-9]+"), ("alnum", r"[A-Za-z0-9]+")):
        if re.fullmatch(pattern, token):
            return name
    return "mixed"


def features(tokens: list[str], at: int, file: str, hide: bool = False) -> list[int]:
    """Hashed features of a token: own shape, neighbouring words and file."""
    t = tokens[at]
    before = [tokens[at - k].lower() if at >= k else "<s>" for k in (1, 2, 3)]
    after = [tokens[at + k].lower() if at + k < len(tokens) else "</s>" for k in (1, 2)]
    kinds = charset(t)
    digits = sum(c.isdigit() for c in t)
    found = ["bias", f"set={kinds}", f"len={min(len(t), 48) // 4}", f"set+len={kinds}{min(len(t), 48) // 4}", f"digits={8 * digits // len(t)}", f"start={t[:4] if t[:4].isupper() else ''}", f"file={file}"]
    turns = sum(a.isdigit() != b.isdigit() for a, b in zip(t, t[1:]))
    found += [f"turns={min(turns, 12) // 2}", f"set+turns={kinds}{min(turns, 12) // 3}", f"distinct={min(len(set(t)), 16) // 2}", f"shape={shape(t)}"]
    found += [f"p1={before[0] if not before[0].isalnum() else '<w>'}", f"n1={after[0] if not after[0].isalnum() else '<w>'}"]
    if not hide:
        found += [f"name{k}={w}" for k, w in enumerate(before) if w.isalnum() and len(w) < 12] + [f"at={'@' in before + after}"]
    return [zlib.crc32(f.encode()) % BUCKETS for f in found]


def file_features(body: bytes | None) -> str:
    if not body:
        return "empty"
    signs = body.count(b"=") + body.count(b"{") + body.count(b";")
    return f"{min(3, 1000 * signs // len(body))}{min(2, 200 * body.count(b'@') // len(body))}{len(body).bit_length() // 3}"


class Field:
    """Weights of states (features x tags) and of moves between tags.

    Rows are (features, may begin) of a token; at a token without one only O is allowed.
    """

    def __init__(self, states: np.ndarray, moves: np.ndarray):
        self.states, self.moves = states, moves

    def scores(self, rows: list[tuple[list[int], bool] | None]) -> np.ndarray:
        out = np.full((len(rows), 3), -1e9)
        out[:, 2] = 0.0
        for i, row in enumerate(rows):
            if row is not None:
                out[i] = self.states[row[0]].sum(axis=0)
                if not row[1]:
                    out[i, 0] = -1e9
        if len(out):
            out[0, 1] = -1e9  # nothing goes on at the start
        return out

    def viterbi(self, rows: list[tuple[list[int], bool] | None]) -> str:
        score = self.scores(rows)
        best, back = score[0], []
        for s in score[1:]:
            step = best[:, None] + self.moves
            back.append(step.argmax(axis=0))
            best = step.max(axis=0) + s
        tag = int(best.argmax())
        path = [tag]
        for b in reversed(back):
            tag = int(b[tag])
            path.append(tag)
        return "".join(TAGS[t] for t in reversed(path))

    def gradient(self, rows, tags: str):
        """Log likelihood and its gradient: observed minus expected, by forward and backward sums."""
        score, gold = self.scores(rows), [TAGS.index(t) for t in tags]
        n = len(rows)
        a, b = np.zeros((n, 3)), np.zeros((n, 3))
        a[0] = score[0]
        for i in range(1, n):
            a[i] = np.logaddexp.reduce(a[i - 1][:, None] + self.moves, axis=0) + score[i]
        for i in range(n - 2, -1, -1):
            b[i] = np.logaddexp.reduce(self.moves + score[i + 1] + b[i + 1], axis=1)
        total = np.logaddexp.reduce(a[-1])
        moves = np.zeros((3, 3))
        for i in range(1, n):
            moves[gold[i - 1], gold[i]] += 1
            moves -= np.exp(a[i - 1][:, None] + self.moves + score[i] + b[i] - total)
        p = np.exp(a + b - total)
        return [(row[0], np.eye(3)[gold[i]] - p[i]) for i, row in enumerate(rows) if row is not None], moves


def train(samples: list[tuple[str, int, int, str, list[tuple[int, int]]]], epochs: int = 4, rate: float = 0.3, decay: float = 1e-4) -> Field:
    """samples: (cut, first, last, file features, values of secrets inside it). Adaptive gradient steps, one cut at a time."""
    field = Field(np.zeros((BUCKETS, 3)), np.array([[0, 0, 0], [0, 0, 0], [0, -1e9, 0]], dtype=float))
    state_sum, move_sum = np.full((BUCKETS, 3), 1e-6), np.full((3, 3), 1e-6)
    allowed = field.moves > -1e8
    random = np.random.default_rng(42)
    for _ in range(epochs):
        for k in random.permutation(len(samples)):
            snippet, first, last, file, values = samples[k]
            tokens = marked(snippet, first, last)
            words = [t[2] for t in tokens]
            hide = random.random() < 0.4
            rows, tags = [], ""
            for i, (s, e, _, mark) in enumerate(tokens):
                of = next((v for v in values if v[0] < e and s < v[1]), None) if mark else None
                goes_on = of is not None and tags[-1:] in ("B", "I") and tokens[i - 1][1] > of[0]
                tags += "I" if goes_on else "B" if of is not None and mark == 2 else "O"
                rows.append((features(words, i, file, hide), mark == 2) if mark else None)
            if not any(r is not None for r in rows):
                continue
            states, moves = field.gradient(rows, tags)
            for row, g in states:
                g = g - decay * field.states[row]
                state_sum[row] += g * g
                field.states[row] += rate * g / np.sqrt(state_sum[row])
            moves = np.where(allowed, moves, 0)
            move_sum += moves * moves
            field.moves += np.where(allowed, rate * moves / np.sqrt(move_sum), 0)
    return field


def decode(field: Field, snippet: str, file: str, first: int = 0, last: int | None = None) -> list[tuple[int, int]]:
    tokens = marked(snippet, first, len(snippet) if last is None else last)
    words = [t[2] for t in tokens]
    if not tokens:
        return []
    tags = field.viterbi([(features(words, i, file), t[3] == 2) if t[3] else None for i, t in enumerate(tokens)])
    out: list[tuple[int, int]] = []
    for (s, e, _, _), tag in zip(tokens, tags):
        if tag == "B":
            out.append((s, e))
        elif tag == "I" and out:
            out[-1] = (out[-1][0], e)
    return out


CUT = "struct<start: int, first: int, last: int, text: string>"
FOUND = f"doc_id long, n_assign long, n_access long, n_hex long, base string, starts array<int>, file string, cuts array<{CUT}>"
RESULT = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_crf long"


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Base spans with the starts of their values, and the cuts around possible secrets, in one pass over the texts."""
    arrow = arrow_schema(docs.sparkSession, FOUND)

    def run(batches):
        for part in chunks(batches):
            rows = []
            for doc, body in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                spans, around = base_spans(body), snippets(body)
                count = [sum(s[0] == k for s in spans) for k in KINDS[:3]]
                spans.sort(key=lambda x: (x[1], KINDS.index(x[0]), x[2]))
                cuts = [dict(zip(("start", "first", "last", "text"), c)) for c in around]
                rows.append((doc, *count, listed([s[:3] for s in spans]), [s[3] for s in spans], file_features(body) if around else "", cuts))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), arrow.types)], schema=arrow)

    return text_bytes(docs, id_col, text_col).mapInArrow(run, FOUND)


def parsed(base: str) -> list[tuple[str, int, int]]:
    return [(k, int(s), int(e)) for k, s, e in (x.split(":") for x in base.split(",") if x)]


def learn(found: DataFrame, sample: int = SAMPLE_CUTS) -> Field | None:
    """The field, from a bounded sample: documents in the order of a hash, half of the cuts from documents with base spans."""
    found = found.where(F.size("cuts") > 0).withColumn("h", F.xxhash64("doc_id", "row"))
    halves = []
    for has in (True, False):
        rows = lowest_hashes(found.where((F.col("base") != "") == has), F.col("h"), sample // 2, "row")
        rows = rows.select("base", "starts", "file", F.slice("cuts", 1, DOCUMENT_CUTS).alias("cuts")).collect()
        cuts = []
        for r in rows:
            values = [(at, e) for (_, _, e), at in zip(parsed(r["base"]), r["starts"])]
            for c in r["cuts"]:
                inside = [(s - c["start"], e - c["start"]) for s, e in values if s < c["start"] + c["last"] and e > c["start"] + c["first"]]
                cuts.append((c["text"], c["first"], c["last"], r["file"], inside))
        halves.append(cuts[: sample // 2])
    cuts = halves[0] + halves[1]
    known = {look(t) for cut in cuts for s, e, t, m in marked(*cut[:3]) if m == 2 and any(lo < e and s < hi for lo, hi in cut[4])}
    if not known:
        return None
    # what looks like a known value but has no name may be a secret: it is no example of either
    clear = [cut for cut in cuts if cut[4] or not any(m == 2 and look(t) in known for _, _, t, m in marked(*cut[:3]))]
    return train(clear)


def look(token: str) -> tuple[str, int]:
    return charset(token), min(len(token), 48) // 4


def find_secrets(docs: DataFrame, sample: int = SAMPLE_CUTS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_crf."""
    spark = docs.sparkSession
    found = checkpoint(scan(docs, id_col, text_col).withColumn("row", F.monotonically_increasing_id()))
    field = spark.sparkContext.broadcast(learn(found, sample))
    arrow = arrow_schema(spark, RESULT)

    def run(batches):
        for part in batches:
            rows = []
            for doc, assign, access, hexes, base, file, cuts in zip(*(c.to_pylist() for c in part.columns)):
                spans, new = parsed(base), []
                for c in cuts if field.value else ():
                    for s, e in decode(field.value, c["text"], file, c["first"], c["last"]):
                        if not any(lo < c["start"] + e and c["start"] + s < hi for _, lo, hi in spans):
                            new.append(("crf", c["start"] + s, c["start"] + e))
                rows.append((doc, assign, access, hexes, hashlib.sha256(base.encode()).hexdigest(), listed(spans + new), len(new)))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), arrow.types)], schema=arrow)

    return found.select("doc_id", "n_assign", "n_access", "n_hex", "base", "file", "cuts").mapInArrow(run, RESULT)
