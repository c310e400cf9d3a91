"""Line-first cleaning.

Each line is judged alone (navigation, boilerplate, missing sentence punctuation on short lines, symbol runs);
failing lines go, and a document is rejected when the cleaned text has lost too large a share of its words.
Whole-document figures (words, repeated windows, symbols, repeated lines) and their base rule come from the
same pass over the words.

Defined results: a null or empty text has no words, fails the base rule and is not kept; texts of any length are read
whole, a few at a time; repeated rows are judged alike; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import re
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import arrow_schema, chunks, text_bytes

WINDOW = 5
#: A document is rejected if its failing lines hold more than this share of its words.
MAX_LOST = 0.5
SYMBOLS = re.compile(rb"[#*$%&|<>]")
#: Phrases of navigation and boilerplate lines (fixed values).
BOILERPLATE = re.compile(
    rb"cookie|privacy policy|terms of (?:use|service)|all rights reserved|copyright|\(c\) \d{4}|javascript|subscribe|newsletter"
    rb"|sign (?:in|up)|log ?in|read more|click here|share (?:this|on)|follow us|lorem ipsum|skip to|licensed under"
)
BLANK = rb"[\x20\x09-\x0D]"
SEPARATOR = re.compile(BLANK + rb"(?:[|>/]|\xc2\xbb)+" + BLANK)
NAVIGATION = re.compile(rb"^[\x20\x09-\x0D]*(?:home|menu|next|previous|back|top|contact|about)\b[\x20\x09-\x0D|>/.]*$")
ENDINGS = tuple(x.encode() for x in (".", "!", "?", ":", ";", ",", '"', "'", ")", "…", "”", "。"))
EXCLAIMED = re.compile(rb"!!|\?\?")


def line_fails(line: bytes, words: list[bytes]) -> str | None:
    """The rule that a line breaks, or None. Lines without words are kept, they carry no text."""
    if not words:
        return None
    low = line.lower()
    n = len(words)
    if n <= 25 and BOILERPLATE.search(low):
        return "boilerplate"
    if line.count(b" | ") + line.count(b" > ") >= 3 or len(SEPARATOR.findall(low)) >= 3 or NAVIGATION.search(low):
        return "navigation"
    if n >= 8 and 4 * len(SYMBOLS.findall(line)) >= 3 * n:
        return "symbols"
    if n >= 8 and 2 * len(EXCLAIMED.findall(line)) >= n:
        return "shouting"
    if n <= 3 and len(line) < 30 and not line.rstrip().endswith(ENDINGS):
        return "punctuation"
    return None


def repeated_words(words: list[bytes], window: int = WINDOW) -> int:
    """Words inside windows that occur twice or more, each word once."""
    if len(words) <= window:
        return 0
    grams = list(zip(*[words[k:] for k in range(window)]))
    if len(set(grams)) == len(grams):
        return 0
    count, end, total = Counter(grams), 0, 0
    for at, gram in enumerate(grams):
        if count[gram] > 1:
            total += at + window - max(at, end)
            end = at + window
    return total


SCHEMA = (
    "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, "
    "kept boolean, lines_removed long, words_removed long"
)


def clean(body: bytes | None) -> tuple[bytes, int, int, list[bytes], list[tuple[bytes, list[bytes]]]]:
    """The text without its failing lines, how many lines and words went, all words, and its lines with their words."""
    body = body or b""
    lines = [(line, line.split()) for line in body.split(b"\n")]
    keep, gone, lost = [], 0, 0
    for line, words in lines:
        if line_fails(line, words):
            gone += 1
            lost += len(words)
        else:
            keep.append(line)
    return b"\n".join(keep), gone, lost, [w for _, words in lines for w in words], lines


def judge(docs: DataFrame, max_lost: float = MAX_LOST, with_text: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Figures and verdict of every document; with_text adds clean_text."""
    schema = SCHEMA + (", clean_text string" if with_text else "")
    arrow = arrow_schema(docs.sparkSession, schema)

    def run(batches):
        for part in chunks(batches):
            rows = []
            for doc, body in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                text, gone, lost, words, lines = clean(body)
                n = len(words)
                seen, repeated = set(), 0
                for line, own in lines:
                    if own:
                        repeated += line in seen
                        seen.add(line)
                again = repeated_words(words)
                chars = len(b"".join(words).decode("utf-8", "replace"))
                failed = n < 10 or 100 * again > 20 * n
                row = (doc, n, chars, len(SYMBOLS.findall(body)) if body else 0, repeated, again, failed, not failed and lost <= max_lost * n, gone, lost)
                rows.append(row + (text.decode("utf-8", "replace"),) if with_text else row)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), arrow.types)], schema=arrow)

    return text_bytes(docs, id_col, text_col).mapInArrow(run, schema)


def oracle() -> str:
    """DuckDB SQL for judge() over documents, from the same patterns."""
    text = lambda pattern: pattern.decode().replace("'", "''")
    count = lambda pattern, size: f"(length(line) - length(regexp_replace(line, '{pattern}', '', 'g'))) / {size}"
    endings = "".join(e.decode() for e in ENDINGS).replace("'", "''")
    return f"""
WITH whole AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS text FROM documents),
lines AS (
    SELECT r, line, translate(line, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS low,
        [x FOR x IN string_split_regex(line, '{text(BLANK)}+') IF x <> ''] AS own
    FROM (SELECT r, unnest(string_split(text, chr(10))) AS line FROM whole)),
judged AS (
    SELECT r, line, len(own) AS n, len(own) > 0 AND (
        (len(own) <= 25 AND regexp_matches(low, '{text(BOILERPLATE.pattern)}'))
        OR {count(r" \| ", 3)} + {count(" > ", 3)} >= 3
        OR len(regexp_extract_all(low, '{text(BLANK)}(?:[|>/]|»)+{text(BLANK)}')) >= 3
        OR regexp_matches(low, '{text(NAVIGATION.pattern)}')
        OR (len(own) >= 8 AND 4 * {count(text(SYMBOLS.pattern), 1)} >= 3 * len(own))
        OR (len(own) >= 8 AND 2 * {count(text(EXCLAIMED.pattern), 2)} >= len(own))
        OR (len(own) <= 3 AND strlen(line) < 30 AND NOT regexp_matches(regexp_replace(line, '{text(BLANK)}+$', ''), '[{endings}]$'))) AS fails
    FROM lines),
by_line AS (
    SELECT r, coalesce(sum(n) FILTER (fails), 0) AS lost, count(*) FILTER (fails) AS gone,
        count(*) FILTER (n > 0) - count(DISTINCT line) FILTER (n > 0) AS dup
    FROM judged GROUP BY r),
words AS (SELECT r, doc_id, text, [x FOR x IN string_split_regex(text, '{text(BLANK)}+') IF x <> ''] AS w FROM whole),
windows AS (SELECT r, pos, w[pos : pos + {WINDOW - 1}] AS gram FROM (SELECT r, w, unnest(range(1, len(w) - {WINDOW - 2})) AS pos FROM words)),
again AS (SELECT r, pos FROM (SELECT r, pos, count(*) OVER (PARTITION BY r, gram) AS c FROM windows) WHERE c > 1),
covered AS (SELECT r, count(DISTINCT pos + k) AS repeated FROM again, range({WINDOW}) AS steps(k) GROUP BY r),
figures AS (
    SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(list_sum([length(x) FOR x IN w]), 0) AS BIGINT) AS word_chars,
        CAST(length(regexp_replace(text, '{text(SYMBOLS.pattern).replace("[", "[^")}', '', 'g')) AS BIGINT) AS n_symbols,
        CAST(dup AS BIGINT) AS n_dup_lines, CAST(coalesce(repeated, 0) AS BIGINT) AS n_repeat_words,
        CAST(gone AS BIGINT) AS lines_removed, CAST(lost AS BIGINT) AS words_removed
    FROM words JOIN by_line USING (r) LEFT JOIN covered USING (r))
SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed,
    NOT (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AND words_removed <= {MAX_LOST} * n_words AS kept
FROM figures"""
