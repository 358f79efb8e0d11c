"""Benchmark decontamination by template canonicalisation.

Numbers, names and units become typed placeholders. Windows of five template tokens meet the windows of the
benchmark in a hash join, and a document holds an item if at least 0.8 of the item's windows are met and the
values in the slots can be mapped onto each other one to one. So a question comes up again even when its
figures and names were changed, while texts that merely share a phrase do not.

The benchmark's windows are a table; only a bit set of fixed size is sent to all tasks, so that a document gives a row
just for the windows that may be there. Texts that meet enough windows of an item are read again, each with its items,
to compare the slots.
"""

from __future__ import annotations

import re
from collections import Counter, defaultdict
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from adapterlab.llm.common import broadcast_within, checkpointed, tables, texts, tidied, with_small_batches

WINDOW, SIMILARITY = 5, 0.8
MIN_WORDS = 2  # words that are no placeholders, in a window
FEW = 5  # items with fewer windows are found by their exact words as well
BITS = 22  # of a window's hash, for the bit set of the benchmark's windows
CHUNK = 1 << 17  # characters of documents coded at once, beside the text that crosses it
ITEMS = 4096  # items a task keeps ready

# Unit words and number words.
UNITS = frozenset(
    "mm cm m km inch inches foot feet ft yard yards mile miles mg g kg gram grams kilogram kilograms ton tons tonne tonnes ounce ounces oz lb lbs pound pounds "
    "ml cl l liter liters litre litres gallon gallons cup cups ms s sec second seconds min minute minutes h hr hour hours day days week weeks month months "
    "year years percent percentage degree degrees celsius fahrenheit kelvin hz khz mhz ghz w kw mw watt watts v volt volts amp amps joule joules calorie "
    "calories kcal n newton newtons pa kpa bar mph kmh kph dollar dollars cent cents euro euros usd eur gbp yen byte bytes kb mb gb tb piece pieces".split()
)
NUMBER_WORDS = frozenset(
    "zero one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen sixteen seventeen eighteen nineteen twenty thirty forty "
    "fifty sixty seventy eighty ninety hundred thousand million billion dozen".split()
)
NUMBER = re.compile(r"[+\-]?[$€£¥]?\d[\d.,:/]*%?")
WITH_UNIT = re.compile(r"([+\-]?[$€£¥]?\d[\d.,:/]*)([^\W\d_]+)")
EDGES = re.compile(r"^[^\w$€£¥+\-]+|[^\w%]+$")
ENDING = frozenset(".!?…:")
LINE = "\x00"

# A word's code: 56 bits of its hash, then the flags below.
IS_NUMBER, IS_UNIT, CAPITAL, ENDS, SKIP, IS_LINE = 1, 2, 4, 8, 16, 32
WORD, NUM, NAME, UNIT = 0, 1, 2, 3


class Codes(dict):
    """Word -> code, made once for each distinct word; emptied when it grows large."""

    LIMIT = 120_000

    def __missing__(self, word: str) -> int:
        if len(self) >= self.LIMIT:
            self.clear()
        trimmed = word.rstrip(".,;:!?…")
        if trimmed.isalpha():  # nearly all words
            low = trimmed.lower()
            flags = ENDS * (trimmed != word and not ENDING.isdisjoint(word[len(trimmed) :])) | CAPITAL * trimmed[0].isupper()
            flags |= IS_NUMBER * (low in NUMBER_WORDS) | IS_UNIT * (low in UNITS)
        elif word == LINE:
            low, flags = "", IS_LINE | SKIP
        else:
            bare = EDGES.sub("", word)
            low = bare.lower()
            flags = ENDS * bool(re.search(r"[.!?…:][^\w]*$", word)) | SKIP * (not bare) | CAPITAL * bare[:1].isupper()
            if NUMBER.fullmatch(bare) or low in NUMBER_WORDS:
                flags |= IS_NUMBER
            elif m := WITH_UNIT.fullmatch(bare):
                flags |= IS_NUMBER | IS_UNIT if m[2].lower() in UNITS else 0
            elif low in UNITS:
                flags |= IS_UNIT
        code = (xxhash.xxh3_64_intdigest(low.encode("utf-8", "surrogatepass")) & ~255 | flags) - (1 << 63)
        self[word] = code
        return code


@dataclass
class Template:
    """Template tokens of one text or of several, one after the other."""

    keys: np.ndarray  # hash of each token, placeholders by their type
    kinds: np.ndarray
    codes: np.ndarray  # hash of each token's own word
    text: np.ndarray  # which text a token belongs to, rising


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(29))


def templates(some: Iterable[str | None], codes: Codes) -> tuple[Template, Template, Template]:
    """Three forms: capitals name something inside sentences; at their start as well; nowhere.

    The second meets names that start a sentence and copies whose sentences start elsewhere, the third copies in all
    small letters.
    """
    words: list[str] = []
    sizes = []
    for text in some:
        before = len(words)
        words += (text or "").replace("\n", f" {LINE} ").split()
        words.append(LINE)  # a text's end ends a sentence
        sizes.append(len(words) - before)
    raw = np.fromiter(map(codes.__getitem__, words), np.int64, len(words))
    of = np.repeat(np.arange(len(sizes)), sizes)
    flags = raw & 255
    # A sentence starts after an end mark, at a new line, and at the beginning.
    breaks = (flags & (ENDS | IS_LINE)) != 0
    starts = np.concatenate([[True], breaks[:-1]])[: len(raw)]
    sentence = np.cumsum(starts)
    keep = (flags & SKIP) == 0
    # Tokens without letters or digits carry a sentence's start on to the next token.
    first = np.zeros(len(raw), bool)
    kept = np.flatnonzero(keep)
    if len(kept):
        first[kept] = np.concatenate([[True], sentence[kept[1:]] != sentence[kept[:-1]]])
    raw, flags, first, sentence, of = raw[keep], flags[keep], first[keep], sentence[keep], of[keep]
    number = (flags & IS_NUMBER) != 0
    after = np.concatenate([[False], number[:-1] & (of[1:] == of[:-1])])[: len(raw)]
    unit = ((flags & IS_UNIT) != 0) & after & ~number
    capital = ((flags & CAPITAL) != 0) & ~number
    # Where most words of a sentence are capitals, capitals name nothing.
    if len(raw):
        loud = np.bincount(sentence, capital) > 0.5 * np.bincount(sentence)
        capital &= ~loud[sentence]
    own = raw.view(np.uint64) >> np.uint64(8)
    plain = np.where(number, NUM, np.where(unit, UNIT, WORD)).astype(np.int8)

    def form(names: np.ndarray) -> Template:
        kinds = np.where(names & (plain == WORD), np.int8(NAME), plain)
        return Template(_mix(np.where(kinds == WORD, own, kinds.astype(np.uint64))), kinds, own, of)

    return form(capital & ~first), form(capital), form(np.zeros(len(raw), bool))


def _hashed(tokens: np.ndarray, text: np.ndarray, width: int) -> np.ndarray:
    """Odd hash of the window at each token; zero where it would cross into the next text."""
    n = len(tokens) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    h = np.zeros(n, np.uint64)
    for j in range(width):
        h = _mix(h * np.uint64(0x9E3779B97F4A7C15) + tokens[j : j + n])
    return np.where(text[:n] == text[width - 1 :], h | np.uint64(1), np.uint64(0))


def windows(t: Template, width: int = WINDOW) -> np.ndarray:
    """Hash of the window at each token; zero for windows with too few words."""
    h = _hashed(t.keys, t.text, width)
    words = np.concatenate([[0], np.cumsum(t.kinds == WORD)])
    return np.where(words[width:] - words[:-width] >= MIN_WORDS, h, np.uint64(0)) if len(h) else h


def word_windows(t: Template, width: int = WINDOW) -> np.ndarray:
    """Hash of the words of the window at each token, whatever their types; other hashes than those of `windows`."""
    h = _hashed(t.codes, t.text, width)
    return np.where(h != 0, _mix(h) | np.uint64(1), h)


def _distinct_forms(forms: tuple[Template, ...]) -> list[Template]:
    return [t for f, t in enumerate(forms) if not any(np.array_equal(t.kinds, forms[g].kinds) for g in range(f))]


@dataclass
class Form:
    """One form of an item."""

    template: Template
    at: dict[int, list[int]]  # window -> its places


@dataclass
class Item:
    forms: list[Form]
    exact: Template | None  # for items with few windows: their words count as they are


def item_of(text: str | None, codes: Codes, width: int = WINDOW) -> Item:
    forms, every = [], templates([text], codes)
    for t in _distinct_forms(every):
        at: dict[int, list[int]] = defaultdict(list)
        for i, h in enumerate(windows(t, width).tolist()):
            if h:
                at[h].append(i)
        if at:
            forms.append(Form(t, at))
    few = max((len(f.at) for f in forms), default=0) < FEW
    return Item(forms, every[0] if few and len(every[0].codes) >= width else None)


class Text:
    """A document's windows by hash, all forms together."""

    def __init__(self, text: str | None, codes: Codes, width: int):
        forms = templates([text], codes)
        self.template, self.width = forms[0], width
        found = [windows(t, width) for t in _distinct_forms(forms)]
        self.by_hash = _sorted_places(np.concatenate(found), np.concatenate([np.arange(len(h)) for h in found]))
        words = word_windows(forms[0], width)
        self.by_words = _sorted_places(words, np.arange(len(words)))

    @staticmethod
    def places(of: tuple[np.ndarray, np.ndarray], key: int) -> list[int]:
        lo, hi = np.searchsorted(of[0], np.uint64(key), "left"), np.searchsorted(of[0], np.uint64(key), "right")
        return np.unique(of[1][lo:hi]).tolist()

    def match(self, item: Item, similarity: float) -> tuple[int, int, int, int] | None:
        """(windows met, windows of the item, slots, slots with another value), or None."""
        best = None
        if (t := item.exact) is not None:
            n = len(t.codes)
            for i in self.places(self.by_words, int(word_windows(t, self.width)[0])):
                if np.array_equal(self.template.codes[i : i + n], t.codes):
                    best = (n - self.width + 1, n - self.width + 1, int((t.kinds != WORD).sum()), 0)
                    break
        for form in item.forms:
            hits = {key: places for key in form.at if (places := self.places(self.by_hash, key))}
            if len(hits) < similarity * len(form.at):
                continue
            if (found := _consistent(self.template, form, hits, self.width, similarity)) is not None:
                row = (found[0], len(form.at), found[1], found[2])
                if best is None or row[0] * best[1] > best[0] * row[1]:
                    best = row
        return best


def _sorted_places(h: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(h, kind="stable")
    return h[order], at[order]


def _consistent(t: Template, item: Form, hits: dict[int, list[int]], width: int, similarity: float) -> tuple[int, int, int] | None:
    """Looks for the item around each diagonal (place in the text minus place in the item); None if it is nowhere whole."""
    diagonals: dict[int, list[tuple[int, int]]] = defaultdict(list)
    for key, places in item.at.items():
        for i in hits.get(key, ()):
            for j in places:
                diagonals[i - j].append((i, j))
    n = len(item.template.keys)
    order = sorted(diagonals)
    reach = max(2, n // 5)  # words put in or left out move a copy to diagonals close by
    best, lo, hi, held, seen = None, 0, 0, 0, None
    for d in order:
        while hi < len(order) and order[hi] <= d + reach:
            held += len(diagonals[order[hi]])
            hi += 1
        while order[lo] < d - reach:
            held -= len(diagonals[order[lo]])
            lo += 1
        if held < similarity * len(item.at) or (lo, hi) == seen:
            continue
        seen = lo, hi
        near = [p for e in order[lo:hi] for p in diagonals[e]]
        keys = {j for _, j in near}
        whole = sum(1 for places in item.at.values() if any(j in keys for j in places))
        if whole < similarity * len(item.at):
            continue
        pairs = [(i, j) for i, j in _aligned(t, item.template, near, width) if item.template.kinds[j] != WORD]
        there: dict[int, Counter] = defaultdict(Counter)
        back: dict[int, Counter] = defaultdict(Counter)
        for i, j in pairs:
            a, b = int(item.template.codes[j]), int(t.codes[i])
            there[a][b] += 1
            back[b][a] += 1
        usual = {a: c.most_common(1)[0][0] for a, c in there.items()}
        origin = {b: c.most_common(1)[0][0] for b, c in back.items()}
        fit = sum(usual[int(item.template.codes[j])] == int(t.codes[i]) and origin[int(t.codes[i])] == int(item.template.codes[j]) for i, j in pairs)
        if pairs and fit < similarity * len(pairs):
            continue
        changed = sum(1 for i, j in pairs if item.template.codes[j] != t.codes[i])
        if best is None or (whole, -changed) > (best[0], -best[2]):
            best = (whole, len(pairs), changed)
        if best[0] == len(item.at) and not best[2]:
            break  # nothing can be better
    return best


def _aligned(t: Template, item: Template, near: list[tuple[int, int]], width: int) -> list[tuple[int, int]]:
    """(place in the text, place in the item) of the tokens in the windows met, rising in both, so that no token counts twice.

    Of all such alignments one with the most tokens, where each change of the diagonal costs a token; equal values decide ties.
    """
    rows: dict[int, set[int]] = defaultdict(set)
    for i, j in near:
        for s in range(width):
            rows[j + s].add(i + s)
    low = min(min(r) for r in rows.values())
    m = max(max(r) for r in rows.values()) - low + 2
    before, before_at = np.zeros(m), np.full(m, -1)  # best chain that ends before a place of the text, and its last token
    along: dict[int, tuple[float, int]] = {}  # the same for each diagonal
    tokens: list[tuple[int, int, int]] = []
    for j in sorted(rows):
        now, now_at = np.full(m, -1.0), np.full(m, -1)
        for i in sorted(rows[j]):
            score, last = along.get(i - j, (-1.0, -1))
            if (other := before[i - low] - (before_at[i - low] >= 0)) > score:
                score, last = other, int(before_at[i - low])
            score += 1 + 0.1 * (t.codes[i] == item.codes[j])
            tokens.append((i, j, last))
            along[i - j] = (score, len(tokens) - 1)
            now[i - low + 1], now_at[i - low + 1] = score, len(tokens) - 1
        better = now > before
        before, before_at = np.where(better, now, before), np.where(better, now_at, before_at)
        top = np.maximum.accumulate(before)
        spot = np.maximum.accumulate(np.where(np.concatenate([[True], before[1:] > top[:-1]]), np.arange(m), 0))
        before, before_at = top, before_at[spot]
    out, k = [], int(before_at[-1])
    while k >= 0:
        out.append(tokens[k][:2])
        k = tokens[k][2]
    return out


DIGEST = "__leak_digest"
MATCHES = "doc_id long, item_id long, matched int, windows int, similarity double, slots int, changed_slots int"
CHECKED = f"{DIGEST} binary, item_id long, matched int, windows int, similarity double, slots int, changed_slots int"


def _digest() -> Column:
    return F.unhex(F.md5(F.coalesce(F.col("text"), F.lit("")))).alias(DIGEST)


def _item_windows(items: DataFrame, width: int, similarity: float) -> DataFrame:
    """(window, item, form, need): the distinct windows of each form, and how many of them a text must meet."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes = Codes()
        for batch in batches:
            for key, text in zip(batch.column("item").to_pylist(), texts(batch.column("text"))):
                item = item_of(text, codes, width)
                rows = [(f, list(form.at), int(np.ceil(similarity * len(form.at)))) for f, form in enumerate(item.forms)]
                if item.exact is not None:
                    rows.append((-1, word_windows(item.exact, width)[:1].tolist(), 1))
                for f, found, need in rows:
                    m = len(found)
                    arrays = [np.array(found, np.uint64).view(np.int64), np.full(m, key, np.int64), np.full(m, f, np.int32), np.full(m, need, np.int32)]
                    yield pa.RecordBatch.from_arrays([pa.array(a) for a in arrays], names=["window", "item", "form", "need"])

    return items.select("item", "text").mapInArrow(run, "window long, item long, form int, need int")


def _bit_set(wanted: DataFrame) -> bytes:
    """One bit for each value of the first BITS bits of a window; 2 ** BITS numbers at most come to the driver."""
    slots = wanted.select(F.shiftrightunsigned("window", 64 - BITS).alias("slot")).distinct().toPandas()["slot"].to_numpy(np.int64)
    seen = np.zeros(1 << BITS, bool)
    seen[slots] = True
    return np.packbits(seen).tobytes()


def _chunks(column: Iterable[str]) -> Iterator[list[str]]:
    some, chars = [], 0
    for t in column:
        some.append(t)
        chars += len(t)
        if chars >= CHUNK:
            yield some
            some, chars = [], 0
    if some:
        yield some


def _hits(documents: DataFrame, bits, width: int) -> DataFrame:
    """Distinct (digest, window) of the texts' windows whose bit is set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen, codes = np.unpackbits(np.frombuffer(bits.value, np.uint8)).view(bool), Codes()
        shift = np.uint64(64 - BITS)

        def among(h: np.ndarray, t: Template) -> tuple[np.ndarray, np.ndarray]:
            spots = np.flatnonzero(seen[(h >> shift).astype(np.int64)])
            spots = spots[h[spots] != 0]
            return t.text[spots], h[spots]

        for batch in batches:
            row = 0
            for some in _chunks(texts(batch.column("text"))):
                forms = templates(some, codes)
                found = [among(windows(t, width), t) for t in forms] + [among(word_windows(forms[0], width), forms[0])]
                at, h = (np.concatenate(x) for x in zip(*found))
                if len(at):
                    pairs = np.unique(np.stack([at.astype(np.uint64), h], axis=1), axis=0)
                    yield pa.RecordBatch.from_arrays([batch.column(DIGEST).take(pa.array(row + pairs[:, 0].astype(np.int64))), pa.array(pairs[:, 1].copy().view(np.int64))], names=[DIGEST, "window"])
                row += len(some)

    return with_small_batches(documents).select(_digest(), "text").mapInArrow(tidied(run), f"{DIGEST} binary, window long").distinct()


def _compare(width: int, similarity: float):
    codes, ready = Codes(), {}

    def run(text: pa.Table, items: pa.Table) -> pa.Table:
        rows = []
        if text.num_rows and items.num_rows:
            digest, document = text.column(DIGEST)[0].as_py(), Text(text.column("text")[0].as_py(), codes, width)
            for key, item_id, body in zip(*(items.column(c).to_pylist() for c in ("item", "item_id", "item_text"))):
                if key not in ready:
                    if len(ready) >= ITEMS:
                        ready.clear()
                    ready[key] = item_of(body, codes, width)
                if (m := document.match(ready[key], similarity)) is not None:
                    rows.append((digest, item_id, m[0], m[1], m[0] / m[1], m[2], m[3]))
        types = [pa.binary(), pa.int64(), pa.int32(), pa.int32(), pa.float64(), pa.int32(), pa.int32()]
        names = [x.split()[0] for x in CHECKED.split(", ")]
        return pa.table([pa.array(c, t) for c, t in zip(zip(*rows) if rows else [[]] * len(types), types)], names=names)

    return run


def _leaks(documents: DataFrame, benchmark: DataFrame, width: int, similarity: float) -> DataFrame:
    """CHECKED: a row for each distinct text and item found in it."""
    spark = documents.sparkSession
    with tables(spark) as written:
        items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), "text").where("text IS NOT NULL")
        items = written(items.withColumn("item", F.monotonically_increasing_id()))
        wanted = written(_item_windows(items, width, similarity))
        hits = _hits(documents, spark.sparkContext.broadcast(_bit_set(wanted)), width)
        met = hits.join(broadcast_within(wanted), "window").groupBy(DIGEST, "item", "form").agg(F.count(F.lit(1)).alias("met"), F.max("need").alias("need"))
        pairs = written(met.where("met >= need").select(DIGEST, "item").distinct())
        named = broadcast_within(pairs.select(F.col(DIGEST).alias("p_digest")).distinct())
        found = documents.select("text", _digest()).join(named, F.col(DIGEST) == F.col("p_digest"), "left_semi")
        found = found.groupBy(DIGEST).agg(F.first("text").alias("text"))  # texts of one digest are equal
        bodies = pairs.join(items.select(F.col("item").alias("i_item"), "item_id", F.col("text").alias("item_text")), F.col("item") == F.col("i_item"))
        asked = bodies.select(DIGEST, "item", "item_id", "item_text")
        return checkpointed(found.groupBy(DIGEST).cogroup(asked.groupBy(DIGEST)).applyInArrow(_compare(width, similarity), CHECKED))


def find_leaks(documents: DataFrame, benchmark: DataFrame, width: int = WINDOW, similarity: float = SIMILARITY) -> DataFrame:
    """One row for each pair of a document and an item found in it.

    (doc_id, item_id, matched, windows, similarity, slots, changed_slots): windows of the item met and in all, their
    ratio, slots compared and slots with another value than the item's. Null and empty texts match nothing, nor
    do items of fewer than `width` tokens. Items with fewer than FEW windows of MIN_WORDS plain words are found by their
    exact words as well, all windows met. Repeated documents or items give a row each. Other columns are not read.
    """
    found = _leaks(documents, benchmark, width, similarity).withColumnRenamed(DIGEST, "l_digest")
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), _digest())
    return docs.join(broadcast_within(found), F.col(DIGEST) == F.col("l_digest")).select(*(x.split()[0] for x in MATCHES.split(", ")))


def drop_leaked(documents: DataFrame, benchmark: DataFrame, width: int = WINDOW, similarity: float = SIMILARITY) -> DataFrame:
    """The rows of `documents`, all columns, that hold no benchmark item.

    Rows with a null id, null or empty texts and repeated rows are kept or dropped by their text alone.
    """
    found = _leaks(documents, benchmark, width, similarity).select(F.col(DIGEST).alias("l_digest")).distinct()
    rows = documents.withColumn(DIGEST, _digest())
    return rows.join(broadcast_within(found), F.col(DIGEST) == F.col("l_digest"), "left_anti").select(*documents.columns)
