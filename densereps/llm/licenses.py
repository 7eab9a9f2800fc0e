"""License scans by conditional compression.

A candidate block is a paragraph, up to the empty lines around it, that has a cue word. Each template is a raw
zstandard dictionary; the text around a cue is compressed alone and with each, and templates rank by how much the
dictionary takes off the size. Down that ranking, the templates are compared with the block word by word: the template
that leaves the fewest words different wins, and it is confirmed when the block holds all but a small share of the
template's words, in order, with every number and every name-like word of the template exact. The RANKED best are compared
in any case, and below them each template that could still be confirmed: one is left out only where the block, in whatever
order, lacks too many of its words or one that must be exact. A confirmed span may go over several blocks, as whole licences
do; what is left before and after it is searched at each cue.

Defined results: a null or empty text has no blocks; of equal templates the one named first wins; a block without a
confirmed span gives its best template; a text's licences are listed once each, in the order of their first blocks. Texts are
read whole; a block of any length is compared whole. Only the text column is read; other columns pass through.
"""

from __future__ import annotations

import re
from bisect import bisect_left, bisect_right
from collections import Counter
from collections.abc import Iterator
from difflib import SequenceMatcher

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densereps.llm.license_templates import templates

#: Words that make a line a candidate. Fixed values.
CUES = rb"licen[sc]e|copyright|permission is|permission to use|redistribut|free software|spdx|cc by|cc0|creative commons"
#: Templates that are compared in any case, and the share of a template's words that may differ.
RANKED, MAX_DIFFERENT = 5, 0.15
#: Words of a template that must be there exactly: numbers, and what tells the licences apart.
EXACT = re.compile(r"^[0-9.]+$|^(mit|apache|bsd|isc|mozilla|gnu|lesser|affero|general|by|sa|nc|cc0|creative|attribution|sharealike|noncommercial|neither|endorse|promote)$")
LEVEL = 3

FOUND = (
    "blocks int, licenses array<string>, matches array<struct<license: string, start: int, bytes: int, saved: double, "
    "different: int, missing: array<string>, added: array<string>, confirmed: boolean>>"
)

#: Bytes before and after a cue by which templates are ranked.
BEFORE, AFTER = 160, 480

_WORD = re.compile(r"[0-9a-z]+(?:\.[0-9]+)*")
_BYTES = re.compile(_WORD.pattern.encode())
_GAP = re.compile(rb"\r?\n(?:[ \t\r]*\n)+")


def tokens(text: str) -> list[str]:
    return _WORD.findall(text.lower())


def blocks(raw: bytes, cue: re.Pattern[bytes]) -> list[tuple[int, int]]:
    """Byte ranges of candidate blocks: the paragraphs, parted by empty or white lines, that have a cue."""
    out: list[tuple[int, int]] = []
    at = 0
    for gap in [*_GAP.finditer(raw), None]:
        end = gap.start() if gap else len(raw)
        if cue.search(raw, at, end):
            out.append((at, end))
        at = gap.end() if gap else end
    return out


def prepare(rows: list[tuple[str, str]], level: int = LEVEL) -> list[dict]:
    """Templates with their dictionaries and words."""
    made = []
    for name, text in rows:
        held = zstandard.ZstdCompressionDict(text.lower().encode(), dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        packer = zstandard.ZstdCompressor(level=level, dict_data=held, write_content_size=False, write_checksum=False)
        words = tokens(text)
        made.append({"license": name, "packer": packer, "words": words, "counts": Counter(words), "exact": {w for w in words if EXACT.match(w)}})
    return made


def wording(template: list[str], block: list[str]) -> tuple[list[str], list[str], tuple[int, int]]:
    """(template words that the block lacks, words it has between them, the block's words from first to last match)."""
    match = SequenceMatcher(None, template, block, autojunk=False)
    top = match.find_longest_match()
    if not top.size:
        return template, [], (0, 0)
    # the words around the longest run that a confirmed notice can take up
    spare = int(MAX_DIFFERENT * len(template)) + 1
    low, high = max(0, top.b - top.a - spare), top.b - top.a + len(template) + spare
    if low or high < len(block):
        match = SequenceMatcher(None, template, block[low:high], autojunk=False)
    real = [m for m in match.get_matching_blocks() if m.size]
    # a chance match at an end that adds more words than it holds is none
    while len(real) > 1 and real[1].b - real[0].b - real[0].size > real[0].size:
        real = real[1:]
    while len(real) > 1 and real[-1].b - real[-2].b - real[-2].size > real[-1].size:
        real = real[:-1]
    first, last = low + real[0].b, low + real[-1].b + real[-1].size
    kept = {i for m in real for i in range(m.a, m.a + m.size)}
    used = {low + i for m in real for i in range(m.b, m.b + m.size)}
    return [w for i, w in enumerate(template) if i not in kept], [block[i] for i in range(first, last) if i not in used], (first, last)


def may_confirm(template: dict, held: Counter[str]) -> bool:
    """Whether a block with these words, in whatever order, may hold the template: no confirmed one fails this."""
    lacking = (template["counts"] - held).total()
    return lacking <= MAX_DIFFERENT * len(template["words"]) and all(w in held for w in template["exact"])


def judge(block: str, prepared: list[dict], plain: zstandard.ZstdCompressor, near: str | None = None) -> dict | None:
    """The winning template of one block, ranked by the text near a cue, with what the wording says of it."""
    low = (block if near is None else near).lower().encode()
    words = tokens(block)
    alone = len(plain.compress(low))
    ranked = sorted(((alone - len(t["packer"].compress(low))) / alone, -i) for i, t in enumerate(prepared))[::-1]
    held, best = Counter(words), None
    for place, (saved, i) in enumerate(ranked):
        t = prepared[-i]
        if place >= RANKED and not may_confirm(t, held):
            continue
        missing, added, span = wording(t["words"], words)
        different = len(missing) + len(added)
        sure = different <= MAX_DIFFERENT * len(t["words"]) and not t["exact"] & set(missing) and not any(EXACT.match(w) for w in added)
        row = {"license": t["license"], "saved": saved, "different": different, "missing": missing, "added": added, "confirmed": sure, "span": span}
        rank = (not sure, different - len(t["words"]) * sure, -saved)
        if best is None or rank < best[0]:
            best = (rank, row)
    return best and best[1]


def judge_all(raw: bytes, cue: re.Pattern[bytes], prepared: list[dict], plain: zstandard.ZstdCompressor) -> list[dict]:
    """The confirmed spans of a text, which may go over several blocks, and the best template of each block without any."""
    low = raw.lower()
    at = [(w.start(), w.end()) for w in _BYTES.finditer(low)]
    starts = [a for a, _ in at]
    # more words than a notice around its cue can have
    reach = max((int((1 + MAX_DIFFERENT) * len(t["words"])) for t in prepared), default=0) + 2
    cues = [m.span() for m in cue.finditer(raw)]
    ranges = blocks(raw, cue)
    best: dict[tuple[int, int], dict] = {}

    def search(begin: int, end: int) -> list[dict]:
        """Confirmed spans among the words from begin to end."""
        sure: list[dict] = []
        for a, b in cues:
            k = bisect_left(starts, a)
            if not begin <= k < end:
                continue
            first, last = max(begin, k - reach), min(end, k + reach)
            near = low[max(at[first][0], a - BEFORE) : min(at[last - 1][1], b + AFTER)].decode(errors="ignore")
            row = judge(" ".join(low[x:y].decode() for x, y in at[first:last]), prepared, plain, near)
            if not row:
                continue
            if row["confirmed"]:
                i, j = first + row["span"][0], first + row["span"][1]
                if i > k:  # the span lies beyond this cue, which is searched again in what is before it
                    sure += search(begin, i)
                sure.append(row | {"start": at[i][0], "bytes": at[j - 1][1] - at[i][0]})
                begin = max(j, begin)
                continue
            block = ranges[bisect_right(ranges, (a, len(raw))) - 1]
            if block not in best or row["different"] < best[block]["different"]:
                best[block] = row | {"start": block[0], "bytes": block[1] - block[0]}
        return sure

    sure = search(0, len(at))
    free = [r for (a, b), r in best.items() if not any(r["start"] < b and a < r["start"] + r["bytes"] for r in sure)]
    return sorted(sure + free, key=lambda r: r["start"])


def scan(texts: pa.Array, prepared: list[dict]) -> pa.Array:
    cue = re.compile(CUES, re.IGNORECASE)
    plain = zstandard.ZstdCompressor(level=LEVEL, write_content_size=False, write_checksum=False)
    out = []
    for text in texts:
        raw = (text.as_py() or "").encode()
        found = judge_all(raw, cue, prepared, plain) if cue.search(raw) else []
        matches = [{k: v for k, v in r.items() if k != "span"} for r in found]
        out.append({"blocks": len(blocks(raw, cue)), "licenses": list(dict.fromkeys(m["license"] for m in matches if m["confirmed"])), "matches": matches})
    kind = pa.struct(
        [
            ("blocks", pa.int32()), ("licenses", pa.list_(pa.string())),
            ("matches", pa.list_(pa.struct([
                ("license", pa.string()), ("start", pa.int32()), ("bytes", pa.int32()), ("saved", pa.float64()), ("different", pa.int32()),
                ("missing", pa.list_(pa.string())), ("added", pa.list_(pa.string())), ("confirmed", pa.bool_()),
            ]))),
        ]
    )
    return pa.array(out, kind)


def scanner(rows: list[tuple[str, str]] | None = None):
    """A column function: text to blocks, licenses and matches; rows are (licence, template)."""
    given = templates() if rows is None else rows

    @F.arrow_udf(FOUND)
    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        prepared = prepare(given)
        for texts in batches:
            yield scan(texts, prepared)

    return run


def scan_licenses(docs: DataFrame, into: str, text_col: str = "text", rows: list[tuple[str, str]] | None = None) -> DataFrame:
    """docs with a struct column into."""
    return docs.withColumn(into, scanner(rows)(F.col(text_col)))
