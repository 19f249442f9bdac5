"""Benchmark decontamination: canonical templates, hashed windows, slot consistency.

A window of a template is the join key. The benchmark's windows are the small side, broadcast behind a count; documents
are hashed where they lie and only hits go on. Every window is a key. An item is laid along a document only if the windows
that the document holds cover enough of it, which loses no leak, so that common windows alone do not multiply.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator

import numpy as np
import pandas as pd
import regex
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semjoin.llm.common import content_key, materialize, without_rows

#: Units of measure that become one placeholder.
UNITS = frozenset("mm cm m km mi miles mile inch inches ft feet yard yards g kg mg lb lbs pound pounds ounce ounces oz ton tons l ml liter liters litre litres gallon gallons s sec second seconds min minute minutes h hr hour hours day days week weeks month months year years dollar dollars cent cents euro euros usd eur percent degree degrees celsius fahrenheit kelvin volt volts watt watts joule joules newton newtons hz khz mhz ghz kb mb gb tb mph kph".split())
NUMBER_WORDS = frozenset("zero one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen sixteen seventeen eighteen nineteen twenty thirty forty fifty sixty seventy eighty ninety hundred thousand million billion".split())
_NUMBER = regex.compile(r"[+-]?\p{Sc}?\p{N}[\p{N}.,:/]*(?:st|nd|rd|th|%|\p{Sc})?")
_NUMBER_UNIT = regex.compile(r"([+-]?\p{N}[\p{N}.,]*)(\p{L}+)")
_EDGE = regex.compile(r"^[^\p{L}\p{N}+\-\p{Sc}]+|[^\p{L}\p{N}%\p{Sc}]+$")
#: Items with fewer tokens than the window match as a whole.
WINDOW = 8
MIN_COVER = 0.5
#: Words of the benchmark that may be broadcast; a larger benchmark goes in groups of items.
MAX_WINDOWS = 2_000_000
#: Words that fill one slot at most.
FILLER = 4
#: Different plain words that a leak with other slot values must share with its item: a table of numbers is no question.
PLAIN = 3
#: Hits of windows that are laid out at a time.
LAID = 1_000_000

_KINDS = ("<number>", "<name>", "<unit>")
_CODE = {k: xxhash.xxh64_intdigest(k.encode(), 7) for k in _KINDS}
_PLACE = np.array(sorted(_CODE.values()), np.uint64)
_NAME = np.uint64(_CODE["<name>"])
_EMPTY = xxhash.xxh64_intdigest(b"", 7)
_MIX = np.uint64(0x2545F4914F6CDD1D)


def _hash(x: str) -> int:
    return xxhash.xxh64_intdigest(x.encode(), 7)


_WORD_CODE = {x: _CODE["<number>"] for x in NUMBER_WORDS} | {x: _CODE["<unit>"] for x in UNITS - NUMBER_WORDS}


def _fact(raw: str) -> tuple[int, int, int, bool, bool]:
    """Of a raw token: hash in lower case, template code, hash of the unit if it is a number and a unit in one, whether it
    could be a name, and whether it ends a sentence."""
    core, stop = raw, False
    if not raw.isalpha():
        last = raw[-1]
        stop = last in ".!?:;"
        core = raw[:-1] if (stop or last == ",") and raw[:-1].isalpha() else _EDGE.sub("", raw)
    low = core if core.islower() else core.lower()
    own = xxhash.xxh64_intdigest(low.encode(), 7)
    code = _WORD_CODE.get(low)
    if code is not None:
        return own, code, 0, False, stop
    if not core.isalpha():
        if _NUMBER.fullmatch(core) or ("-" in low and all(x in NUMBER_WORDS for x in low.split("-"))):
            return own, _CODE["<number>"], 0, False, stop
        if (m := _NUMBER_UNIT.fullmatch(core)) and m[2].lower() in UNITS:
            return _hash(m[1].lower()), _CODE["<number>"], _hash(m[2].lower()), False, stop
    return own, own, 0, core is not low and core[:1].isupper() and not core.isupper(), stop


_OTHER = _hash("<other>")


class Lexicon(dict):
    """raw token -> its number, under which columns() has its facts. Emptied between texts when it is full. With the
    words of a benchmark, plain words that are not among them need no hash: they are all one, and match nothing."""

    FULL = 120_000

    def __init__(self, words: frozenset | None = None):
        super().__init__()
        self.words = words
        self.clear()

    def clear(self) -> None:
        super().clear()
        self.new: list[tuple] = [(_OTHER, _OTHER, 0, False, False), (_OTHER, _OTHER, 0, False, True)]
        self.size = 0
        self.table = [np.zeros(1 << 12, t) for t in (np.uint64, np.uint64, np.uint64, bool, bool)]

    def __missing__(self, raw: str) -> int:
        if self.words is not None:
            if raw.isalpha():
                if raw not in self.words and raw.islower():
                    return 0
            elif (last := raw[-1]) in ".,!?:;" and (core := raw[:-1]).isalpha() and core not in self.words and core.islower():
                return int(last != ",")
        self[raw] = at = self.size + len(self.new)
        self.new.append(_fact(raw))
        return at

    def columns(self) -> list[np.ndarray]:
        """The facts as arrays, by number; what is new since the last call is added."""
        if self.new:
            end = self.size + len(self.new)
            if end > len(self.table[0]):
                self.table = [np.concatenate([x, np.zeros(max(end, 2 * len(x)) - len(x), x.dtype)]) for x in self.table]
            for column, facts in zip(self.table, zip(*self.new, strict=True), strict=True):
                column[self.size : end] = facts
            self.new, self.size = [], end
        return self.table


def canonical(text: str, lexicon: Lexicon, first_is_name: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of each token: a hash of its own words, its template code, and whether it is a slot.

    Numbers and units become placeholders; so does a capitalised word that does not start a line or a
    sentence, as a name. Neighbours of one kind are one slot, filled by all their words: "Mary Ann" is one name, "twenty
    five" one number; more than FILLER of them are a list, which stays as it is. 40km is a number and a unit. Tokens are runs of anything but white space, stripped of
    punctuation at their ends; tokens of punctuation alone are dropped.
    """
    if len(lexicon) > Lexicon.FULL:
        lexicon.clear()
    ids, starts = [], []
    for line in text.split("\n"):
        tokens = line.split()
        if tokens:
            starts.append(len(ids))
            ids += map(lexicon.__getitem__, tokens)
    none = np.zeros(0, np.uint64)
    if not ids:
        return none, none, np.zeros(0, bool)
    at = np.array(ids)
    own, code, pair, name, stop = (x[at] for x in lexicon.columns())
    first = np.zeros(len(at), bool)
    first[1:] = stop[:-1]
    first[starts] = True
    first[0] &= not first_is_name
    code[name & ~first] = _NAME
    if pair.any():
        again = 1 + (pair != 0)
        unit = np.cumsum(again)[pair != 0] - 1
        own, code = np.repeat(own, again), np.repeat(code, again)
        own[unit], code[unit] = pair[pair != 0], _CODE["<unit>"]
    some = own != np.uint64(_EMPTY)
    own, code = own[some], code[some]
    slots = own != code
    if not len(own):
        return none, none, slots
    more = np.zeros(len(own), bool)
    more[1:] = slots[1:] & slots[:-1] & (code[1:] == code[:-1])
    if more.any():
        head = np.nonzero(~more)[0]
        listed = np.repeat(np.diff(np.append(head, len(own))) > FILLER, np.diff(np.append(head, len(own))))
        if listed.any():
            code, slots, more = np.where(listed, own, code), slots & ~listed, more & ~listed
            head = np.nonzero(~more)[0]
        with np.errstate(over="ignore"):
            place = np.arange(len(own)) - np.repeat(head, np.diff(np.append(head, len(own))))
            mixed = np.where(place > 0, (own ^ (own >> np.uint64(31))) * (_MIX + np.uint64(2) * place.astype(np.uint64)), own)
            own = np.add.reduceat(mixed, head)
        code, slots = code[head], slots[head]
    return own, code, slots


def window_hashes(own: np.ndarray, codes: np.ndarray, slots: np.ndarray, size: int) -> np.ndarray:
    """Hash of each window of `size` codes: a polynomial modulo 2**64. A window of placeholders alone says
    nothing, so it is hashed by the tokens themselves."""
    n = len(codes) - size + 1
    if n <= 0:
        return np.zeros(0, np.uint64)

    def poly(x: np.ndarray) -> np.ndarray:
        out = np.zeros(n, np.uint64)
        for i in range(size):
            out = out * _MIX + x[i : i + n]
        out ^= out >> np.uint64(29)
        return out * np.uint64(0xBF58476D1CE4E5B9) ^ np.uint64(size)

    with np.errstate(over="ignore"):
        out = poly(codes)
        upto = np.concatenate([[0], np.cumsum(slots)])
        bare = upto[size:] - upto[:-size] == size
        if bare.any():
            out[bare] = poly(own)[bare] ^ np.uint64(1)
    return out


def own_hashes(own: np.ndarray, size: int) -> np.ndarray:
    """Hash of each window by the tokens themselves."""
    return window_hashes(own, own, np.ones(len(own), bool), size)


class Index:
    """Windows of a benchmark: sorted hashes with the template and position of each, and the templates' tokens. Items
    shorter than the window have templates as they are, with a name for their first word, and without it, as
    what stands before a short item decides what its first word is taken for."""

    def __init__(self, items: list[tuple[int, str]], window: int):
        lexicon = Lexicon()
        words = set(NUMBER_WORDS | UNITS)
        self.window, self.ids, self.items, self.sizes, self.whole, self.enough = window, [], [], [], [], []
        hashes, item, at = [], [], []

        def add(item_id: int, tokens: tuple, whole: int) -> None:
            size = min(window, len(tokens[0]))
            # Without plain words enough for other slot values, only windows that agree word for word count.
            enough = not tokens[2].any() or plain_words(tokens, [(0, len(tokens[0]))]) >= PLAIN
            h = window_hashes(*tokens, size) if enough else own_hashes(tokens[0], size)
            self.enough.append(enough)
            hashes.append(h)
            item.append(np.full(len(h), len(self.ids)))
            at.append(np.arange(len(h)))
            self.ids.append(item_id)
            self.items.append(tokens)
            self.sizes.append(size)
            self.whole.append(whole)

        for item_id, text in items:
            tokens = canonical(text or "", lexicon)
            words.update(_EDGE.sub("", x).lower() for x in (text or "").split())
            n = len(tokens[0])
            if not n:
                continue
            add(item_id, tokens, n)
            if n <= window:
                named = canonical(text, lexicon, True)
                if not np.array_equal(named[1], tokens[1]):
                    add(item_id, named, len(named[0]))
                if n > 4:
                    add(item_id, tuple(x[1:] for x in tokens), n)
        self.words = frozenset(words)
        flat = np.concatenate(hashes) if hashes else np.zeros(0, np.uint64)
        which = np.concatenate(item) if item else np.zeros(0, np.int64)
        place = np.concatenate(at) if at else np.zeros(0, np.int64)
        order = np.argsort(flat, kind="stable")
        self.hashes, self.item, self.at = flat[order], which[order], place[order]
        self.size_of = np.array(self.sizes, np.int64)[self.item]
        self.lengths = sorted(set(self.sizes))
        # Of each template: the tokens in windows of slots alone, whose codes may agree where their hashes do not.
        self.bare = np.array([bare_tokens(x[2], size) for x, size in zip(self.items, self.sizes, strict=True)], np.int64)
        self.wholes = np.array(self.whole, np.int64)


def bare_tokens(slots: np.ndarray, size: int) -> int:
    """How many tokens lie in windows of slots alone."""
    upto = np.concatenate([[0], np.cumsum(slots)])
    bare = np.nonzero(upto[size:] - upto[:-size] == size)[0]
    return int(np.minimum(np.diff(bare), size).sum()) + size if len(bare) else 0


def covered_enough(index: Index, entries: np.ndarray, min_cover: float) -> np.ndarray:
    """Which templates can have min_cover of their tokens in runs, if these windows (numbers in the index, distinct) are all
    that a document holds: each token of a run lies in such a window, or in one of slots alone."""
    entries = entries[np.lexsort((index.at[entries], index.item[entries]))]
    item, at, size = index.item[entries], index.at[entries], index.size_of[entries]
    cover = size.copy()
    cover[:-1] = np.where(item[1:] == item[:-1], np.minimum(at[1:] - at[:-1], size[:-1]), size[:-1])
    total = np.bincount(item, cover, len(index.ids))
    return (total > 0) & (total + index.bare >= min_cover * index.wholes)


def runs_on(shift: int, doc: tuple, tokens: tuple, size: int) -> list[tuple[int, int]]:
    """(start, end) in the template of the runs of `size` equal codes or more, with the template laid at this shift.
    Runs of placeholders alone must be equal word for word."""
    lo, hi = max(0, -shift), min(len(tokens[1]), len(doc[1]) - shift)
    if hi - lo < size:
        return []
    same = doc[1][lo + shift : hi + shift] == tokens[1][lo:hi]
    edge = np.diff(np.concatenate([[0], same.view(np.int8), [0]]))
    out = []
    for a, b in zip((np.nonzero(edge == 1)[0] + lo).tolist(), (np.nonzero(edge == -1)[0] + lo).tolist(), strict=True):
        if b - a >= size and not (tokens[2][a:b].all() and not np.array_equal(doc[0][a + shift : b + shift], tokens[0][a:b])):
            out.append((a, b))
    return out


def fillers(doc: tuple, tokens: tuple, a: int, b: int, shift: int, there: dict, back: dict) -> int | None:
    """How many slots of a run are filled anew, with the fillers noted both ways; None, and nothing noted, if they do not
    map one to one."""
    at = np.nonzero(tokens[2][a:b])[0] + a
    new, changed = [], 0
    for d, i in zip(doc[0][at + shift].tolist(), tokens[0][at].tolist(), strict=True):
        if there.get(i, d) != d or back.get(d, i) != i:
            for i, d in new:
                del there[i], back[d]
            return None
        if i not in there:
            there[i], back[d] = d, i
            new.append((i, d))
        changed += d != i
    return changed


def agree_until(doc: tuple, tokens: tuple, a: int, b: int, shift: int, there: dict, back: dict) -> int:
    """Up to which token of a run the fillers agree with those noted and with each other."""
    at = np.nonzero(tokens[2][a:b])[0] + a
    own_there, own_back = {}, {}
    for k, d, i in zip(at.tolist(), doc[0][at + shift].tolist(), tokens[0][at].tolist(), strict=True):
        if there.get(i, d) != d or back.get(d, i) != i or own_there.setdefault(i, d) != d or own_back.setdefault(d, i) != i:
            return k
    return b


def plain_words(tokens: tuple, spans: list[tuple[int, int]]) -> int:
    """How many different words that are no slots the spans of a template hold."""
    return len(set().union(*[tokens[1][a:b][~tokens[2][a:b]].tolist() for a, b in spans]))


def near_chain(doc: tuple, tokens: tuple, runs: list[tuple[int, int, int]], span: int) -> tuple[int, int, int]:
    """A good chain, quickly: the longest run leads; others join, the longest first, if they fit those taken, which gives way
    to what is already there. chain() starts from it."""
    best = (0, 0, 0)
    left = sorted(runs, key=lambda r: (r[0] - r[1], r[0] + r[2]))
    while left:
        lead, taken, there, back, rest = left[0], [], {}, {}, []
        changed = cover = 0
        for run in left:
            a, b, shift = run
            if abs(a + shift - lead[0] - lead[2]) > span:
                rest.append(run)
                continue
            for x, y, other in taken:
                # Trim what overlaps in the item or in the document; the order must be the same in both.
                if x <= a:
                    cut = max(0, y - a, y + other - a - shift)
                    a = a + cut
                else:
                    b = b - max(0, b - x, b + shift - x - other)
            if a >= b:
                continue
            n = fillers(doc, tokens, a, b, shift, there, back)
            if n is not None:
                taken.append((a, b, shift))
                cover, changed = cover + b - a, changed + n
        if (-cover, changed) < (-best[0], best[1]) and (not changed or plain_words(tokens, [x[:2] for x in taken]) >= PLAIN):
            best = (cover, changed, min((a + s for a, _, s in taken), default=0))
        left = rest
    return best


def chain(doc: tuple, tokens: tuple, runs: list[tuple[int, int, int]], span: int, need: float = 0) -> tuple[int, int, int]:
    """(tokens covered, changed slots, start in the document) of a chain of runs (start, end, shift) of `need` tokens or more:
    if near_chain() has none, the one of most tokens, then fewest changed slots. With no `need`, always that one.

    The runs of a chain start in the same order in the item and in the document, within `span` tokens of one of them, and
    their slot fillers agree; near_chain() may also take one that starts in another order, from where it follows. Where two overlap, one gives way, and what they share counts once.

    All chains are tried that could still be better than the best so far: of what follows a part of a chain, `most` has the
    tokens if no fillers disagreed."""
    runs = sorted(set(runs), key=lambda r: (r[0] + r[2], r[0], r[1]))
    inside = np.zeros(len(tokens[0]) + 1, np.int64)
    for a, b, _ in runs:
        inside[a] += 1
        inside[b] -= 1
    covered = int((np.cumsum(inside) > 0).sum())
    if covered < need:
        return 0, 0, 0
    best = near_chain(doc, tokens, runs, span)
    if len(runs) < 2 or best[:2] == (covered, 0) or 0 < need <= best[0]:
        return best
    first, end, shift = np.array(runs, np.int64).T
    at = first + shift
    most, until = end - first, np.searchsorted(at, at + 2 * span, "right")
    since = np.searchsorted(at, at, "right")

    def after(i: int) -> tuple[np.ndarray, np.ndarray]:
        """Runs that can follow run i, and the tokens that each and what follows it can add."""
        later = np.arange(since[i], until[i])
        later = later[first[later] > first[i]]
        return later, most[later] - np.maximum(0, np.maximum(end[i] - first[later], end[i] + shift[i] - at[later]))

    for i in range(len(runs) - 1, -1, -1):
        most[i] += max(0, int(after(i)[1].max(initial=0)))
    there, back, spans = {}, {}, []

    def worse(cover: int, changed: int) -> bool:
        return cover < need or (-cover, changed) >= (-best[0], best[1])

    def take(lo: int, hi: int, shift: int) -> tuple[int, list, list]:
        """Note the fillers of these tokens, which agree."""
        old, new = len(there), len(back)
        n = fillers(doc, tokens, lo, hi, shift, there, back)
        spans.append((lo, hi))
        return n, list(there)[old:], list(back)[new:]

    def drop(taken: tuple[int, list, list]) -> None:
        spans.pop()
        for known, keys in ((there, taken[1]), (back, taken[2])):
            for k in keys:
                del known[k]

    def grow(i: int, lo: int, cover: int, changed: int, start: int, head: int, center: int) -> None:
        """Chains whose last run is i, from token lo on. cover and changed: of the runs before it; head: where the first run
        starts, center: the last start within span of that."""
        nonlocal best
        a, b, move = runs[i]
        if worse(cover + int(most[i]) - lo + a, changed):
            return
        far = agree_until(doc, tokens, lo, b, move, there, back)
        if far == b:
            whole = take(lo, b, move)
            n = changed + whole[0]
            if not worse(cover + b - lo, n) and (not n or plain_words(tokens, spans) >= PLAIN):
                best = (cover + b - lo, n, start)
            drop(whole)
        later, add = after(i)
        add += cover + b - lo
        # Where the earlier run ends if it gives way.
        early = np.minimum(first[later], at[later] - move)
        some = (add >= max(need, best[0])) & ((far == b) | ((early > lo) & (early <= far) & (early < b)))
        some &= at[later] <= max(head, center) + span
        order = np.argsort(-add[some], kind="stable")
        for j, most_of, stop in zip(later[some][order].tolist(), add[some][order].tolist(), early[some][order].tolist(), strict=True):
            if worse(most_of, changed):
                break
            c, d, other = runs[j]
            middle = c + other if c + other <= head + span else center
            # The later run gives way, or the earlier one.
            ways = [(b, max(c, b, b + move - other))] if far == b else []
            if lo < stop < b and stop <= far:
                ways.append((stop, c))
            for stop, go in ways:
                if go < d:
                    part = take(lo, stop, move)
                    grow(j, go, cover + stop - lo, changed + part[0], start, head, middle)
                    drop(part)

    sys.setrecursionlimit(max(sys.getrecursionlimit(), 1_000 + 2 * len(tokens[0])))
    for i in np.argsort(-most, kind="stable").tolist():
        grow(i, runs[i][0], 0, 0, int(at[i]), int(at[i]), int(at[i]))
    return best


def spread(lo: np.ndarray, many: np.ndarray) -> np.ndarray:
    """lo[0], lo[0] + 1, ... (many[0] numbers), lo[1], ..."""
    ends = np.cumsum(many)
    return np.repeat(lo - ends + many, many) + np.arange(ends[-1] if len(ends) else 0)


def leaks_in(text: str, index: Index, lexicon: Lexicon, min_cover: float) -> list[tuple]:
    """(item_id, start token, tokens, item tokens, changed slots) of the best leak of each item."""
    doc = canonical(text, lexicon)
    hits, far = [], 1 << 40
    for size in index.lengths:
        h = window_hashes(*doc, size)
        if not len(h):
            continue
        each = [h]
        if not all(index.enough):
            each.append(own_hashes(doc[0], size))
        for h in each:
            lo = np.searchsorted(index.hashes, h, "left")
            hit = np.nonzero(index.hashes[np.minimum(lo, len(index.hashes) - 1)] == h)[0]
            if len(hit):
                hits.append((size, hit, lo[hit], np.searchsorted(index.hashes, h[hit], "right") - lo[hit]))
    if not hits:
        return []
    held = []
    for size, _, lo, many in hits:
        lo, first = np.unique(lo, return_index=True)
        entry = spread(lo, many[first])
        held.append(entry[index.size_of[entry] == size])
    fits = covered_enough(index, np.unique(np.concatenate(held)), min_cover)
    if not fits.any():
        return []
    laid_out = np.zeros(0, np.int64)
    for size, hit, lo, many in hits:
        ends = np.cumsum(many)
        for part in np.split(np.arange(len(hit)), np.searchsorted(ends, np.arange(LAID, ends[-1], LAID))):
            entry, place = spread(lo[part], many[part]), np.repeat(hit[part], many[part])
            keep = (index.size_of[entry] == size) & fits[index.item[entry]]
            entry, place = entry[keep], place[keep]
            laid_out = np.union1d(laid_out, index.item[entry] * (2 * far) + place - index.at[entry] + far)
    items, starts = np.unique(laid_out // (2 * far), return_index=True)
    found = zip(items.tolist(), np.split(laid_out % (2 * far) - far, starts[1:]) if len(items) else [], strict=True)
    best: dict[int, tuple] = {}
    for i, laid in found:
        tokens, size, whole, item_id = index.items[i], index.sizes[i], index.whole[i], index.ids[i]
        runs: list[tuple[int, int, int]] = []
        n = len(tokens[0])
        # Shifts at which slots are filled alike come first; a whole item ends the search. Without plain words enough, runs
        # must be equal word for word.
        slot = np.nonzero(tokens[2])[0]
        probes = np.unique(slot[[0, len(slot) // 3, len(slot) // 2, -1]]) if len(slot) else slot
        agree = sum(((doc[0][np.clip(laid + k, 0, len(doc[0]) - 1)] == tokens[0][k]).astype(int) for k in probes), np.zeros(len(laid), int))
        enough = index.enough[i]
        for shift in laid[np.argsort(-agree, kind="stable")].tolist():
            on = runs_on(shift, doc, tokens, size) if enough else runs_on(shift, (doc[0], doc[0]), (tokens[0], tokens[0], tokens[2]), size)
            runs += [(a, b, shift) for a, b in on]
            if on == [(0, n)] and fillers(doc, tokens, 0, n, shift, {}, {}) is not None:
                runs = runs[-1:]
                break
        cover, changed, start = chain(doc, tokens, runs, 2 * whole, min_cover * whole)
        if cover >= min_cover * whole and (item_id not in best or (-cover, changed) < (-best[item_id][1], best[item_id][3])):
            best[item_id] = (start, cover, whole, changed)
    return [(item_id, *x) for item_id, x in best.items()]


SCHEMA = "doc_id long, item_id long, start_token long, n_tokens long, item_tokens long, changed_slots long"


def _search(docs: DataFrame, index: Index, min_cover: float) -> DataFrame:
    """docs: doc_id, two hashes of the text, text."""
    known = docs.sparkSession.sparkContext.broadcast(index)
    names = [x.split()[0] for x in f"{SCHEMA}, __h1 long, __h2 long".split(", ")]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        index = known.value
        lexicon = Lexicon(index.words)
        for pdf in batches:
            rows = [(d, *x, h1, h2) for d, h1, h2, t in zip(pdf["doc_id"], pdf["__h1"], pdf["__h2"], pdf["text"], strict=True) for x in leaks_in(t, index, lexicon, min_cover)]
            out = pd.DataFrame(rows, columns=names)
            yield out.astype({c: "Int64" for c in out.columns})

    return docs.mapInPandas(run, f"{SCHEMA}, __h1 long, __h2 long")


def keyed_leaks(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, min_cover: float = MIN_COVER, max_windows: int = MAX_WINDOWS) -> DataFrame:
    """leaks() with the two hashes of the text, so that rows which share an id are told apart."""
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.coalesce("text", F.lit("")).alias("text"))
    words = items.agg(F.sum(F.regexp_count("text", F.lit(r"\S+"))).alias("n")).first()["n"] or 0
    parts = -(-words // max_windows) or 1
    _, h1, h2 = content_key("doc_id", "text")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), h1, h2, F.coalesce("text", F.lit("")).alias("text"))
    out = None
    for p in range(parts):
        part = items if parts == 1 else items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(parts)) == p)
        found = _search(docs, Index([(r["item_id"], r["text"]) for r in part.toLocalIterator()], window), min_cover)
        out = found if out is None else out.union(found)
    return out


def leaks(docs: DataFrame, benchmark: DataFrame, **params) -> DataFrame:
    """Rows (doc_id, item_id, start_token, n_tokens, item_tokens, changed_slots): each document that holds
    a benchmark item, whole or in a part of min_cover of its tokens, verbatim or with other slot values.

    Texts become templates (canonical()); windows of `window` tokens are joined by hash against the
    benchmark's windows. A hit lays the item along the document; runs of equal tokens of the window's length or more
    are chained in the item's order, so tokens put in or left out between them do no harm; the slot values of a chain
    must map one to one, and with other values than the item's PLAIN different plain words must be shared. Items shorter than the window match as a whole. One leak of an item is reported for a row of
    docs: a place where all of it stands, those that agree word for word looked at first, or else a chain of min_cover
    of the tokens, looked for until there is one or none can be left.

    The benchmark's index is broadcast, so it is built for at most max_windows words at a time, counted
    first; a larger benchmark is split by item id into as many parts as that takes, each searched by a pass of its
    own. Null texts are empty; items without words match nothing; null ids are carried;
    empty tables give no rows; repeated rows are reported each. Extra columns are not read.
    """
    return keyed_leaks(docs, benchmark, **params).drop("__h1", "__h2")


def without_leaks(docs: DataFrame, benchmark: DataFrame, **params) -> DataFrame:
    """docs without the rows that leaks() reports: of two texts that share an id, only the one that holds an item goes.
    Rows with null ids stay. Columns stay as they are."""
    found = keyed_leaks(docs, benchmark, **params).where("doc_id is not null")
    return without_rows(docs, materialize(found.select(F.col("doc_id").alias("__id"), "__h1", "__h2").distinct(), "leaks"))
