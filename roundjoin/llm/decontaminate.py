"""Benchmark decontamination: an occurrence with at most k edits leaves one of k + 1 pieces of the item intact; piece hits are verified by
Myers's bit-parallel edit distance.

Items are the side of bounded size: they go to the tasks in blocks of at most BLOCK_CHARS characters, and each block is one pass
over the documents, so a benchmark of any size works.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import DOC_COLUMNS, pick

#: Production values. One edit is allowed per CHARS_PER_EDIT normalised characters of an item, none in items of fewer than MIN_ITEM_CHARS.
CHARS_PER_EDIT, MIN_ITEM_CHARS, BLOCK_CHARS = 15, 16, 4_000_000
#: Letters of scripts that are written without spaces between words.
_SPACELESS = re.compile("[\u0e00-\u0eff\u1000-\u109f\u1780-\u17ff\u2e80-\u9fff\uf900-\ufaff\uff66-\uff9f\U00020000-\U0003ffff]")


def normalised(text: str | None) -> str:
    """Lower case, white space runs as one space, none at the ends."""
    return " ".join((text or "").lower().split())


def bounded_distance(pattern: str, text: str, budget: int, anchored: bool = False) -> tuple[int, int] | None:
    """Least edit distance, at most budget, between pattern and a substring of text (a prefix if anchored), with the substring's first such end."""
    m = len(pattern)
    eq: dict[str, int] = {}
    for i, c in enumerate(pattern):
        eq[c] = eq.get(c, 0) | (1 << i)
    full, top = (1 << m) - 1, 1 << (m - 1)
    up, down, score, best = full, 0, m, None
    for at, c in enumerate(text):
        hit = eq.get(c, 0)
        zero = (((hit & up) + up) ^ up) | hit | down
        rise, fall = down | (full & ~(zero | up)), zero & up
        if rise & top:
            score += 1
        elif fall & top:
            score -= 1
        if score <= budget and (best is None or score < best[0]):
            best = (score, at + 1)
            if score == 0:
                break
        rise = ((rise << 1) | anchored) & full
        up, down = ((fall << 1) | (full & ~(zero | rise))) & full, rise & zero
    return best


def bounded(text: str, begin: int, end: int) -> bool:
    """Whether text[begin:end] begins and ends between words; letters of scripts without spaces are words of their own."""
    return not any(0 < at < len(text) and all(c.isalnum() and not _SPACELESS.match(c) for c in text[at - 1 : at + 1]) for at in (begin, end))


def pieces_of(item: str, budget: int) -> list[tuple[str, int]]:
    """budget + 1 consecutive pieces of an item, with their offsets."""
    cuts = [len(item) * j // (budget + 1) for j in range(budget + 2)]
    return [(item[a:b], a) for a, b in zip(cuts, cuts[1:], strict=False)]


class Matcher:
    """Finds the occurrences of a block of items in normalised texts."""

    def __init__(self, items: list[tuple[int, str]], chars_per_edit: int, min_item_chars: int = MIN_ITEM_CHARS):
        self.items, self.short = {}, min_item_chars
        found: dict[str, list[tuple[int, int]]] = {}
        for number, (item_id, text) in enumerate(items):
            budget = len(text) // chars_per_edit if len(text) >= min_item_chars else 0
            self.items[number] = (item_id, text, budget)
            for piece, offset in pieces_of(text, budget):
                found.setdefault(piece, []).append((number, offset))
        self.auto = ahocorasick.Automaton()
        for piece, uses in found.items():
            self.auto.add_word(piece, (len(piece), uses))
        if found:
            self.auto.make_automaton()
        self.empty = not found

    def hits(self, text: str) -> Iterator[tuple[int, int, int, int]]:
        """item_id, distance, start and end in the normalised text: for each item and each stretch of nearby piece hits the best occurrence."""
        if self.empty or not text:
            return
        begins: dict[int, set[int]] = {}
        for end, (size, uses) in self.auto.iter(text):
            for number, offset in uses:
                begins.setdefault(number, set()).add(end + 1 - size - offset)
        for number, starts in sorted(begins.items()):
            item_id, item, budget = self.items[number]
            done = -1
            for s in sorted(starts):
                if s < done or len(item) < self.short and not bounded(text, s, s + len(item)):
                    continue
                if s >= 0 and text.startswith(item, s):
                    yield item_id, 0, s, s + len(item)
                    done = s + len(item) - budget
                    continue
                lo = max(0, s - budget)
                window = text[lo : s + len(item) + budget]
                if got := bounded_distance(item, window, budget):
                    back = bounded_distance(item[::-1], window[: got[1]][::-1], got[0], True)
                    yield item_id, got[0], lo + got[1] - back[1], lo + got[1]
                    done = lo + got[1] - budget


def _blocks(benchmark: DataFrame, block_chars: int) -> Iterator[list[tuple[int, str]]]:
    """Distinct usable items, in blocks whose size is checked."""
    items = pick(benchmark, "item_id", "text").where("item_id is not null and text is not null").select(F.col("item_id").cast("long").alias("item_id"), "text").distinct()
    total = items.agg(F.coalesce(F.sum(F.length("text")), F.lit(0)).alias("c"), F.coalesce(F.max(F.length("text")), F.lit(0)).alias("m")).first()
    n = max(1, -(-2 * int(total.c) // block_chars)) if total.c > block_chars // 2 else 1
    for k in range(n):
        rows = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == k).collect()
        usable = sorted((r.item_id, t) for r in rows if (t := normalised(r.text)))
        if usable:
            yield usable


def contaminated(docs: DataFrame, benchmark: DataFrame, chars_per_edit: int = CHARS_PER_EDIT, min_item_chars: int = MIN_ITEM_CHARS, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """doc_id, item_id, distance, hit_start, hit_end (in the normalised text) for each occurrence of an item in a document.

    Null and empty texts have none; items that are null, empty or have a null id are left out; items of fewer than min_item_chars normalised characters are
    found without edits and between words only; repeated items count once, repeated documents each; of overlapping occurrences of one item the first that verifies is given;
    empty tables give no rows; other columns are ignored."""
    body = pick(docs, "doc_id", "text").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    names = ("doc_id", "item_id", "distance", "hit_start", "hit_end")
    schema = "doc_id long, item_id long, distance int, hit_start long, hit_end long"
    out = None
    for block in _blocks(benchmark, block_chars):

        def run(batches, block=block):
            matcher = Matcher(block, chars_per_edit, min_item_chars)
            for b in batches:
                found = [(d, *h) for d, t in zip(b.column("doc_id").to_pylist(), b.column("text").to_pylist(), strict=True) for h in matcher.hits(normalised(t))]
                cols = list(zip(*found, strict=True)) or [[]] * 5
                yield pa.record_batch([pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64()), strict=True)], names=list(names))

        part = body.mapInArrow(run, schema)
        out = part if out is None else out.union(part)
    return out if out is not None else docs.sparkSession.createDataFrame([], schema)


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, chars_per_edit: int = CHARS_PER_EDIT, min_item_chars: int = MIN_ITEM_CHARS, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """The rows of docs in which no item occurs, with the columns of documents. Edge cases as in contaminated; no shuffle."""
    body = pick(docs, *DOC_COLUMNS)
    for block in _blocks(benchmark, block_chars):

        def run(batches, block=block):
            matcher = Matcher(block, chars_per_edit, min_item_chars)
            for b in batches:
                yield b.filter(pa.array([next(matcher.hits(normalised(t)), None) is None for t in b.column("text").to_pylist()], pa.bool_()))

        body = body.mapInArrow(run, body.schema)
    return body
