"""Benchmark decontamination by template canonicalisation.

Texts and benchmark items become sequences of canonical tokens: words in lower
case, with typed placeholders for numbers, for names (capitalised words inside
a sentence) and for units after a number; neighbouring placeholders of a type
merge. A capitalised word that opens a sentence may be a name or not, so it has
both readings. Windows of canonical tokens are hash-joined. A text's windows that meet
an item on one diagonal form an alignment, and its slots must be consistent:
one value of the item always stands against one value of the text.
"""

from __future__ import annotations

import re
from collections import defaultdict
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import packed, textnum

#: Canonical tokens in a window, and how many of them must be words rather than placeholders.
WINDOW, LITERAL = 8, 4
#: The same for items that have too few such windows; their slots must then be of the item's form.
FEW = 3
#: An alignment counts if it covers this many tokens, or this share (in hundredths) of a shorter item.
COVER, SHARE = 13, 80
#: Gaps of this many tokens do not end an alignment (a changed word, a merged or split number).
GAP = 12
#: Benchmarks up to this many words are held by every worker (about 80 bytes a word); larger ones meet the texts by key.
INDEX_WORDS = 2_000_000
#: Shared windows that are laid out at once; a text that shares more is met by some items at a time.
HITS = 1_000_000

# Words that are units when they follow a number.
UNITS = """
mm cm m km in inch inches ft foot feet yd yard yards mi mile miles mg g gram grams kg kilo kilos t ton tons oz lb
pound pounds ml l litre litres liter liters gallon gallons ms s sec secs second seconds min mins minute minutes h hr
hrs hour hours day days week weeks month months year years percent pct degree degrees c f k w kw mw v kv j kj hz khz
mhz ghz b kb mb gb tb usd eur gbp dollar dollars euro euros cent cents mph kmh
""".split()

# Words that open sentences and are no names.
OPENERS = """
a about after all although an and another any are as at because before both but by calculate can compute consider could
did do does during each either every explain few find first for from given has have he her here his how i if in into is
it its let many most my next no not now of on one only or other our please prove second several she show since so solve
some suppose that the their then there these they this those to under until was we were what when where which while who
whose why will with would write you your
""".split()

_U = np.uint64
_STOP = np.ones(256, bool)
_STOP[[*range(0x30, 0x3A), *range(0x41, 0x5B), *range(0x61, 0x7B), *range(0x80, 0x100)]] = False
_DIGIT = np.zeros(256, bool)
_DIGIT[0x30:0x3A] = True
_ENDS = np.zeros(256, bool)
_ENDS[[0x21, 0x2E, 0x3A, 0x3F, 0x0A, 0x0D]] = True
NUMBER, NAME, UNIT = (textnum.mix(np.array([x], _U))[0] for x in (101, 102, 103))
_NUMBER = re.compile(rb"[0-9]+(?:[.,][0-9]+)*")
_KINDS = np.array([NUMBER, NAME, UNIT], _U)


def _lowered(raw: np.ndarray) -> np.ndarray:
    """A-Z and the two-byte Latin-1 capitals in lower case; every byte keeps its place."""
    low = textnum._LOWER[raw]
    if len(raw) > 1:
        second = np.zeros(len(raw), bool)
        second[1:] = (raw[:-1] == 0xC3) & (raw[1:] >= 0x80) & (raw[1:] <= 0x9E) & (raw[1:] != 0x97)
        low[second] += 0x20
    return low


class Canonical:
    """Canonical tokens of documents: hash, document, and the bytes each stands for."""

    def __init__(self, raw: np.ndarray, off: np.ndarray):
        low = _lowered(raw)
        w = textnum.words(low, off, stop=_STOP)
        doc = np.repeat(np.arange(len(off) - 1), w.counts)
        h, s = w.hashes.copy(), w.starts
        if len(h):
            head = np.zeros(len(h), bool)
            head[w.first[:-1][w.counts > 0]] = True
            number = _DIGIT[raw[s]]
            breaks = np.concatenate([[0], np.cumsum(_ENDS[raw])])
            opening = head.copy()
            opening[1:] |= breaks[s[1:]] > breaks[w.ends[:-1]]
            last = w.ends - 1
            nxt = np.minimum(s + 1, last)
            plain = (raw[s] >= 0x41) & (raw[s] <= 0x5A)
            latin = (raw[s] == 0xC3) & (raw[nxt] >= 0x80) & (raw[nxt] <= 0x9E)
            after = np.minimum(s + np.where(latin, 2, 1), last)
            shout = (raw[after] >= 0x41) & (raw[after] <= 0x5A) & (after > s)
            capital = (plain | latin) & ~shout
            name = capital & ~opening
            maybe = capital & opening & ~np.isin(h, _hashes(OPENERS))
            unit = np.isin(h, _hashes(UNITS))
            unit[1:] &= number[:-1] & ~head[1:]
            unit[0] = False
            h[number], h[name], h[unit] = NUMBER, NAME, UNIT
            maybe &= ~unit
            same = np.zeros(len(h), bool)
            same[1:] = (h[1:] == h[:-1]) & np.isin(h[1:], _KINDS) & ~head[1:]
            keep = np.flatnonzero(~same)
            until = np.concatenate([keep[1:], [len(h)]]) - 1
            h, doc, maybe, self.starts, self.ends = h[keep], doc[keep], maybe[keep], s[keep], w.ends[until]
        else:
            self.starts = self.ends = s
            maybe = np.zeros(0, bool)
        self.raw = w
        self.hashes, self.doc, self.low = h, doc, low
        self.first = np.searchsorted(doc, np.arange(len(off)))
        self.literal = ~np.isin(h, _KINDS)
        #: The other reading, in which words that open a sentence are names too.
        self.named, self.maybe = np.where(maybe, NAME, h), maybe
        self.word = self.literal & ~maybe

    def windows(self, n: int, literal: int) -> tuple[np.ndarray, np.ndarray]:
        """Hashes and places of the windows that hold enough words, in both readings where they differ."""
        view = textnum.Words(self.hashes, self.first, self.starts, self.ends)
        h, at = view.windows(n)
        count = np.concatenate([[0], np.cumsum(self.literal)])
        keep = count[at + n] - count[at] >= literal
        if not self.maybe.any():
            return h[keep], at[keep]
        other = np.concatenate([[0], np.cumsum(self.maybe)])
        count = np.concatenate([[0], np.cumsum(self.word)])
        at2 = at[(other[at + n] > other[at]) & (count[at + n] - count[at] >= literal)]
        h2 = textnum.mix(textnum._spans(self.named, at2, at2 + n) + _U(n))
        return np.concatenate([h[keep], h2]), np.concatenate([at[keep], at2])

    def value(self, at: int) -> bytes:
        return self.low[self.starts[at] : self.ends[at]].tobytes()


@cache
def _hashes_of(words: tuple[str, ...]) -> np.ndarray:
    raw, off = textnum.buffers(pa.array(words))
    return textnum.words(raw, off).hashes


def _hashes(words: list[str]) -> np.ndarray:
    return _hashes_of(tuple(words))


class Plain:
    """The words of documents as they stand, without placeholders."""

    def __init__(self, of: Canonical):
        w = of.raw
        self.hashes, self.starts, self.ends, self.first, self.low = w.hashes, w.starts, w.ends, w.first, of.low
        self.doc = np.repeat(np.arange(len(w.counts)), w.counts)

    def windows(self, n: int, literal: int) -> tuple[np.ndarray, np.ndarray]:
        return textnum.Words(self.hashes, self.first, self.starts, self.ends).windows(n)


def _need(size: int | np.ndarray) -> int | np.ndarray:
    """Tokens of an item of this size that an alignment must cover."""
    return np.minimum(COVER, -(-size * SHARE // 100))


class Groups:
    """Windows of the chosen items by length, ready to be met by texts."""

    def __init__(self, items: Canonical | Plain, literal: int, chosen: np.ndarray | None = None):
        self.items, self.literal = items, literal
        self.size = np.diff(items.first)
        self.groups = []
        reached = np.zeros(len(items.hashes), bool)
        for n in sorted({min(WINDOW, int(x)) for x in (self.size if chosen is None else self.size[chosen]) if x >= 3}):
            h, at = items.windows(n, min(literal, n))
            mine = np.minimum(self.size[items.doc[at]], WINDOW) == n
            if chosen is not None:
                mine &= chosen[items.doc[at]]
            h, at = h[mine], at[mine]
            for k in range(n):
                reached[at + k] = True
            order = np.argsort(h, kind="stable")
            self.groups.append((n, h[order], at[order]))
        #: Items that a copy of themselves would match.
        self.whole = (np.bincount(items.doc[reached], minlength=len(self.size)) >= _need(self.size)) & (self.size >= 3)

    def hits(self, text: Canonical | Plain) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Places in the texts and in the items at which a window is shared, and its length; all of an item's come together.

        Runs of shared windows too short for any item are left out, so openings
        that many items have in common cost little unless more follows.
        """
        for n, keys, places in self.groups:
            h, at = text.windows(n, min(self.literal, n))
            if not len(keys) or not len(h):
                continue
            lo = np.searchsorted(keys, h)
            hit = np.flatnonzero(keys[np.minimum(lo, len(keys) - 1)] == h)
            own = self.items.doc[places]
            hit = hit[_reaching(at[hit], n, int(_need(self.size[own]).min()))]
            if not len(hit):
                continue
            lo, up, at = lo[hit], np.searchsorted(keys, h[hit], "right"), at[hit]
            if (up - lo).sum() <= HITS:
                yield _pairs(at, lo, up, places, n)
                continue
            # How often the texts hold each window of the benchmark tells how many hits an item has.
            often = np.zeros(len(keys) + 1, np.int64)
            np.add.at(often, lo, 1)
            np.add.at(often, up, -1)
            total = np.cumsum(np.bincount(own, np.cumsum(often)[:-1], len(self.size)))
            turn = (total // HITS)[own]
            for k in np.unique(turn):
                some = np.concatenate([[0], np.cumsum(turn == k)])
                yield _pairs(at, some[lo], some[up], places[turn == k], n)


def _reaching(at: np.ndarray, n: int, need: int) -> np.ndarray:
    """Which windows lie in runs that cover `need` tokens at least, whatever the item; gaps as in an alignment."""
    order = np.argsort(at, kind="stable")
    step = np.diff(at[order], prepend=at[order][:1] - (1 << 40))
    run = np.cumsum(step > GAP + WINDOW) - 1
    covered = np.bincount(run, np.minimum(step, n)) if len(at) else np.zeros(0)
    out = np.zeros(len(at), bool)
    out[order] = covered[run] >= need
    return out


def _pairs(at: np.ndarray, lo: np.ndarray, up: np.ndarray, places: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    count = up - lo
    place = np.repeat(lo - (np.cumsum(count) - count), count) + np.arange(count.sum())
    return np.repeat(at, count), places[place], np.full(len(place), n)


class Index:
    """Windows of benchmark items: of most items those with enough words, of the others what there is.

    Items that would not match a copy of themselves are met by windows of FEW
    words, and word by word as they stand.
    """

    def __init__(self, ids: list[int], texts: list[str]):
        raw, off = textnum.buffers(pa.array(texts, pa.string()))
        self.ids, items = ids, Canonical(raw, off)
        self.most = Groups(items, LITERAL)
        self.few = Groups(items, FEW, ~self.most.whole)
        self.plain = Groups(Plain(items), 0, ~self.most.whole)


def _form(value: bytes, number: bool) -> bytes | int:
    """What re-parameterising keeps of a slot: a number's text around its digits, how many words a name has."""
    return _NUMBER.sub(b"0", b"".join(value.split())) if number else len(value.split())


def _alike(text: Canonical, items: Canonical, pairs: list[tuple[int, int]]) -> bool:
    """Whether all slots have the form of the item's and none contradicts another."""
    if _consistent(text, items, pairs, True)[0]:
        return False
    slots = [(a, b) for a, b in pairs if not items.word[b] and text.named[a] == items.named[b]]
    return all(_form(text.value(a), items.named[b] == NUMBER) == _form(items.value(b), items.named[b] == NUMBER) for a, b in slots)


def _consistent(text: Canonical, items: Canonical, pairs: list[tuple[int, int]], named: bool) -> tuple[int, int]:
    """How many slots are at odds with one assignment of text values to item values, and how many differ from the item.

    With `named`, words that open a sentence are slots too.
    """
    mine, its = (text.named, items.named) if named else (text.hashes, items.hashes)
    literal = items.word if named else items.literal
    votes: dict[tuple, dict[bytes, int]] = defaultdict(lambda: defaultdict(int))
    slots = []
    for a, b in pairs:
        if not literal[b] and mine[a] == its[b]:
            slots.append(((int(its[b]), items.value(b)), text.value(a)))
            votes[slots[-1][0]][slots[-1][1]] += 1
    best = {k: max(sorted(v), key=v.get) for k, v in votes.items()}
    return sum(best[k] != v for k, v in slots), sum(k[1] != v for k, v in slots)


def _aligned(text: Canonical | Plain, index: Groups) -> Iterator[tuple[int, int, int, list[tuple[int, int]]]]:
    """(document, item, tokens covered, places in both) of each alignment that covers enough."""
    for a, b, n in index.hits(text):
        doc, item = text.doc[a], index.items.doc[b]
        diagonal = (a - text.first[doc]) - (b - index.items.first[item])
        order = np.lexsort((a, diagonal, item, doc))
        a, b, n, doc, item, diagonal = (x[order] for x in (a, b, n, doc, item, diagonal))
        same = (doc[1:] == doc[:-1]) & (item[1:] == item[:-1])
        near = same & (np.abs(diagonal[1:] - diagonal[:-1]) <= 3)
        cut = np.concatenate([[0], np.flatnonzero(~near) + 1, [len(a)]])
        # What neighbouring diagonals cover one by one bounds what they cover together.
        fresh = n.copy()
        line = same & (diagonal[1:] == diagonal[:-1])
        fresh[1:][line] = np.minimum(n[1:], a[1:] - a[:-1])[line]
        enough = np.add.reduceat(fresh, cut[:-1]) >= _need(index.size[item[cut[:-1]]]) if len(a) else np.zeros(0, bool)
        for lo, hi in zip(cut[:-1][enough].tolist(), cut[1:][enough].tolist()):
            by = np.argsort(a[lo:hi], kind="stable") + lo
            far = np.flatnonzero(np.diff(a[by]) > GAP + WINDOW) + 1
            for run in np.split(by, far):
                pairs = sorted({(int(x) + k, int(y) + k) for x, y, m in zip(a[run], b[run], n[run]) for k in range(m)})
                covered = len({y for _, y in pairs})
                if covered >= _need(int(index.size[item[lo]])):
                    yield int(doc[lo]), int(item[lo]), covered, pairs


def _alignments(text: Canonical, index: Index) -> Iterator[tuple[int, int, int, int, int, int, int, int]]:
    """(document, item, tokens covered, item length, first, last byte, slots changed, slots at odds) of each alignment that counts.

    Slots at odds rule an alignment out if they do in both readings. Items met
    by few words need slots that all agree; what is left of their copies as
    they stand has words for tokens.
    """
    items = index.most.items

    def span(tokens: Canonical | Plain, pairs: list[tuple[int, int]]) -> tuple[int, int]:
        return int(tokens.starts[pairs[0][0]]), int(tokens.ends[pairs[-1][0]])

    for doc, item, covered, pairs in _aligned(text, index.most):
        for named, literal in ((True, text.word), (False, text.literal)):
            odds, changed = _consistent(text, items, pairs, named)
            if 4 * odds <= int((~literal[pairs[0][0] : pairs[-1][0] + 1]).sum()):
                yield doc, item, covered, int(index.most.size[item]), *span(text, pairs), changed, odds
                break
    seen = defaultdict(list)
    for doc, item, covered, pairs in _aligned(text, index.few) if index.few.groups else ():
        if _alike(text, items, pairs):
            seen[doc, item].append(span(text, pairs))
            yield doc, item, covered, int(index.few.size[item]), *span(text, pairs), _consistent(text, items, pairs, True)[1], 0
    plain = Plain(text) if index.plain.groups else None
    for doc, item, covered, pairs in _aligned(plain, index.plain) if plain else ():
        first, last = span(plain, pairs)
        if all(last <= lo or first >= hi for lo, hi in seen[doc, item]):
            yield doc, item, covered, int(index.plain.size[item]), first, last, 0, 0


_SCHEMA = "doc_id long, item_id long, n_covered long, n_item long, first_char long, last_char long, slots_changed long, slots_at_odds long"
_TYPES = [(f.split()[0], pa.int64()) for f in _SCHEMA.split(", ")]


def _small(items: DataFrame) -> Index | None:
    """The index of a benchmark of at most INDEX_WORDS words (counted before anything is fetched), else nothing."""
    words = items.agg(F.sum(F.size(F.split("text", r"\s+")))).first()[0] or 0
    if words > INDEX_WORDS:
        return None
    rows = items.orderBy("item_id", "text").collect()
    return Index([r["item_id"] for r in rows], [r["text"] for r in rows])


def _kinds(index: Index) -> list[tuple[int, np.ndarray, np.ndarray]]:
    """(tag, windows, items) of an index: what texts must hold of canonical (even tags) and plain windows (odd tags)."""
    out = []
    for group in (index.most, index.few, index.plain):
        for n, keys, places in group.groups:
            out.append((2 * n + (group is index.plain), keys, group.items.doc[places]))
    return out


def _tagged(h: np.ndarray, tag: int) -> np.ndarray:
    return textnum.mix(h + _U(tag) * textnum._STEP)


def _by_key(source: DataFrame, items: DataFrame) -> DataFrame:
    """Rows of `matches` where the benchmark is large: windows meet in buckets, and each block of texts gets the items it shares one with.

    A block tells every bucket each of its windows once, however often it
    stands there; a bucket answers with the items that hold one of them, each
    once. Nothing is broadcast, and the texts are read from one exchange.
    """
    items = packed.cut(items.withColumn("row", F.monotonically_increasing_id()))
    by = packed.deal(source, "text")
    parts = packed.blocks(source, "id", "text", by)

    def held(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = batch.column(0).to_numpy()
            found = [(tag, _tagged(keys, tag), rows[own]) for tag, keys, own in _kinds(Index(rows.tolist(), batch.column(1).to_pylist()))]
            for tag, keys, own in found:
                out = packed.send(tag, keys, by.buckets, items=own)
                yield pa.record_batch([pa.array(out["block"], pa.int32()), pa.array(out["bucket"], pa.int32()), pa.array(out["keys"], pa.binary()), pa.array(out["items"], pa.binary())], names=["tag", "bucket", "keys", "items"])

    bench = packed.cut(items.select("row", "text").mapInArrow(held, "tag int, bucket int, keys binary, items binary"))
    tags = sorted(r["tag"] for r in bench.select("tag").distinct().collect())

    def emit(group: tuple, table: pa.Table) -> pa.Table:
        raw, off = textnum.buffers(table.column("text"))
        every = [np.zeros(0, _U)]
        for lo, hi in _cuts(off):
            canon = Canonical(raw[off[lo] : off[hi]], off[lo : hi + 1] - off[lo])
            plain = Plain(canon) if any(t % 2 for t in tags) else None
            every += [np.unique(_tagged((plain if t % 2 else canon).windows(t // 2, min(FEW, t // 2))[0], t)) for t in tags]
        return pa.table(packed.send(group[0].as_py(), np.unique(np.concatenate(every)), by.buckets), sent_as)

    def answer(asked: pa.Table, bench: pa.Table) -> pa.Table:
        keys, rows = packed.gathered(bench, "keys", _U), packed.gathered(bench, "items", np.int64)
        order = np.argsort(keys, kind="stable")
        keys, rows = keys[order], rows[order]
        out: dict[str, list] = {"to": [], "row": []}
        for block, sent in zip(asked.column("block").to_pylist(), asked.column("keys").to_pylist()):
            h = np.frombuffer(sent, _U)
            lo, up = np.searchsorted(keys, h), np.searchsorted(keys, h, "right")
            some = np.unique(_pairs(np.zeros(len(h), np.int64), lo, up, rows, 0)[1])
            if len(some):
                out["to"].append(block)
                out["row"].append(some)
        return pa.table(out, pa.schema([("to", pa.int32()), ("row", pa.list_(pa.int64()))]))

    def find(texts: pa.Table, mine: pa.Table) -> pa.Table:
        rows: list[tuple] = []
        if texts.num_rows and mine.num_rows:
            mine = mine.combine_chunks().sort_by([("item_id", "ascending"), ("text", "ascending")])
            ids = texts.column("id").to_pylist()
            rows = [(ids[k], *rest) for k, *rest in _leaks(texts.column("text"), Index(mine.column("item_id").to_pylist(), mine.column("text").to_pylist()))]
        cols = list(zip(*rows)) or [()] * len(_TYPES)
        return pa.table({n: pa.array(c, t) for c, (n, t) in zip(cols, _TYPES)})

    sent_as = pa.schema([("block", pa.int32()), ("bucket", pa.int32()), ("keys", pa.binary())])
    sent = parts.groupBy("block").applyInArrow(emit, "block int, bucket int, keys binary").repartition(by.tasks, "bucket")
    pairs = sent.groupBy("bucket").cogroup(bench.groupBy("bucket")).applyInArrow(answer, "to int, row array<long>")
    wanted = pairs.select("to", F.explode("row").alias("row")).distinct().join(items, "row").select(F.col("to").alias("block"), "item_id", "text")
    return parts.groupBy("block").cogroup(wanted.groupBy("block")).applyInArrow(find, _SCHEMA)


def _cuts(off: np.ndarray) -> Iterator[tuple[int, int]]:
    """Runs of texts of about CHUNK bytes."""
    at = 0
    while at < len(off) - 1:
        to = max(at + 1, int(np.searchsorted(off, off[at] + textnum.CHUNK, "right")) - 1)
        yield at, to
        at = to


def _leaks(column: pa.Array, index: Index) -> Iterator[tuple[int, ...]]:
    """(place of the text, item, tokens covered, item length, first, last byte, slots changed, at odds)."""
    raw, off = textnum.buffers(column)
    for at, to in _cuts(off):
        canon = Canonical(raw[off[at] : off[to]], off[at : to + 1] - off[at])
        for doc, own, covered, size, lo, hi, changed, odds in _alignments(canon, index):
            shift = off[at] - off[at + doc]
            yield at + doc, index.ids[own], covered, size, int(lo + shift), int(hi + shift), changed, odds


def _items(benchmark: DataFrame, item: str, text: str) -> DataFrame:
    return benchmark.select(F.col(item).cast("long").alias("item_id"), F.col(text).alias("text")).where("item_id is not null and text is not null")


def matches(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text", item: str = "item_id", item_text: str = "text") -> DataFrame:
    """One row for each alignment of a text with a benchmark item whose slots are consistent.

    An item is leaked where at least COVER canonical tokens of it, or SHARE
    per cent of a shorter item, stand in the text in order. `slots_changed`
    counts placeholders whose value differs from the item's: above 0 the
    question was re-parameterised. Alignments in which more than a quarter of
    the slots contradict each other are dropped. first_char and last_char
    are byte places in the text (last exclusive).

    Items with too few words beside placeholders to be met so are met where
    FEW words of a window agree, all slots have the form of the item's and
    none contradicts another, and where they stand word by word (n_covered
    and n_item then count words). Null or empty texts and items match
    nothing, as do items of fewer than three words. Repeated rows each
    give their own matches, and so do repeated items. A null document id stays
    null; null item ids are left out. Empty tables give no rows; other columns
    are not read.

    A benchmark of at most INDEX_WORDS words is held by every worker, texts
    are read once and not shuffled; a larger one meets them by key, with the
    same rows. Windows are shared on 64-bit hashes; an alignment rests on
    several of them and its slots are compared as they stand.
    """
    source = docs.select(F.col(key).cast("long").alias("id"), F.col(text).alias("text"))
    items = _items(benchmark, item, item_text)
    index = _small(items)
    if index is None:
        return _by_key(source, items)
    shared = docs.sparkSession.sparkContext.broadcast(index)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0).to_pylist()
            rows = [(ids[doc], *rest) for doc, *rest in _leaks(batch.column(1), shared.value)]
            cols = list(zip(*rows)) or [()] * len(_TYPES)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(cols, _TYPES)], names=[n for n, _ in _TYPES])

    return source.mapInArrow(run, _SCHEMA)


def clean(docs: DataFrame, benchmark: DataFrame, text: str = "text", item: str = "item_id", item_text: str = "text") -> DataFrame:
    """The rows of docs, all columns, whose text holds no benchmark item as `matches` finds them.

    Rows without text stay, as do all rows if the benchmark is empty. With a
    benchmark of at most INDEX_WORDS words nothing is shuffled.
    """
    items = _items(benchmark, item, item_text)
    index = _small(items)
    if index is None:
        rows = packed.cut(docs.withColumn("__row", F.monotonically_increasing_id()))
        found = _by_key(rows.select(F.col("__row").alias("id"), F.col(text).alias("text")), items).select(F.col("doc_id").alias("__found")).distinct()
        return rows.join(found, F.col("__row") == F.col("__found"), "left_anti").drop("__row")
    place = docs.columns.index(text)
    shared = docs.sparkSession.sparkContext.broadcast(index)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        textnum.settle()
        for batch in batches:
            keep = np.ones(batch.num_rows, bool)
            keep[[doc for doc, *_ in _leaks(batch.column(place), shared.value)]] = False
            yield batch.filter(pa.array(keep))
            del batch
            textnum.settle()

    return docs.mapInArrow(run, docs.schema)
