"""Operator 2: all links of n-gram sets with a Jaccard similarity of at least num / 100, by PartEnum signatures.

Sets are put into families by the size of the smaller member of a pair. In a family the similarity bounds the symmetric
difference of a pair by k. The domain of n-grams is hashed into blocks and each block into parts; the blocks are so many
that a pair differs in one or two grams at most in more than `spare` of them, and of each block all subsets of its parts
are enumerated that leave out as many parts as may differ. The hash of a set's share of such a subset is a signature. A
subset of which a set has no gram says nothing and gives none; a pair can then miss all signatures only if both sets
lack grams of the same more than `spare` subsets, so sets that lack so many give signatures of choices of those. No
pair is lost, whatever its size. Equal sets count once.

1. Texts give (signature, set) rows. A task that has a signature of many sets sends one of them on and links the others
   to it, so a signature that a third of all sets share reaches its partition a few times a task.
2. In a bucket of few sets all pairs are candidates; in a crowd each set is one with a centre of its share of the crowd.
3. Candidates are sifted by sketches (parities of grams in bins: they differ in no more bins than the sets in grams),
   then compared by their whole sets, one copy of each set for a cluster of candidates, or a pair of blocks of a large one.
4. Crowds whose sets are not all in one component by then are compared across components, blocks against blocks, by
   sketches and then by whole sets: first each set with its nearest, then all pairs of what is still apart.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache
from itertools import combinations
from math import comb, exp, lgamma, log

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from packvec.llm import text_kernel as K
from packvec.llm.common import bounded, written
from packvec.llm.components import Forest, components

#: Sets in a block of a large cluster or crowd; sets of a bucket whose pairs are all candidates; sets of a signature that a task sends on.
BLOCK, FEW, SENT = 512, 6, 4
#: Signatures that a task gathers before it looks which sets share them; rows of buckets held at once; bins of the smallest sketch.
GATHERED, HELD, BINS = 2_000_000, 400_000, 64
#: Parts of the single block for k of 1 to 4.
SINGLE = {1: 12, 2: 9, 3: 8, 4: 8}
#: Lacking subsets that make a choice, at most.
CHOICE = 4


def most_different(total, num: int):
    """The largest symmetric difference of two linked sets whose sizes add up to total."""
    return total - 2 * ((num * total + 99 + num) // (100 + num))


@lru_cache(maxsize=None)
def _families(num: int, largest: int) -> tuple[tuple[int, int, int], ...]:
    out, low = [], 1
    while low <= largest:
        high = max(low, low * 100 // num)
        top = high * 100 // num
        k = max(most_different(t, num) for t in range(max(2 * low, high + top - 64), high + top + 1))
        out.append((low, top, k))
        low = high + 1
    return tuple(out)


def families(num: int, largest: int) -> tuple[tuple[int, int, int], ...]:
    """(least size, largest size of a partner, k) of each family up to the size `largest` or a little more."""
    return _families(num, 1 << max(largest, 1).bit_length())


@lru_cache(maxsize=None)
def scheme(k: int, low: int) -> tuple[int, int, int, int]:
    """(blocks, parts of a block, parts of a subset, spare blocks) for sets of low grams or more that differ in k at most:
    with the spare blocks that make for the fewest signatures, choices of lacking subsets included."""
    if k in SINGLE:
        return 1, SINGLE[k], SINGLE[k] - k, 0
    differ, parts, least = (2, 5, 1) if k <= 16 else (1, 3, 3)
    best = None
    for spare in range(least, k // 4 + 6):
        blocks = k // (differ + 1) + 1 + spare
        subsets = blocks * comb(parts, differ)
        bare = subsets * (1 - (parts - differ) / (parts * blocks)) ** low
        chance = exp(-bare + spare * log(bare) - lgamma(spare + 1))  # of `spare` lacking subsets, as if independent
        choices, e = 0.0, spare
        while e < spare + 2 * bare + 40:
            e += 1
            chance *= bare / e
            choices += chance * comb(e - spare - 1 + min(CHOICE, spare + 1), min(CHOICE, spare + 1))
        if best is None or subsets + choices < best[0]:
            best = subsets + choices, (blocks, parts, parts - differ, spare)
    return best[1]


def gram_sets(hashes: np.ndarray, firsts: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(grams, where each text's begin): distinct hashes of n words, ascending; a shorter text has one of all its words."""
    counts = np.diff(firsts)
    grams = K.gram_hashes(hashes, n)
    sizes = np.where(counts < n, np.minimum(counts, 1), counts - n + 1)
    begins = np.r_[0, np.cumsum(sizes)]
    values = np.empty(begins[-1], np.uint64)
    full = np.flatnonzero(counts >= n)
    values[K.ragged(begins[full], sizes[full])] = grams[K.ragged(firsts[full], sizes[full])]
    for i in np.flatnonzero((counts > 0) & (counts < n)):
        values[begins[i]] = K.gram_hashes(hashes[firsts[i] : firsts[i + 1]], int(counts[i]))[0] ^ np.uint64(counts[i])
    for a, b in zip(begins[full].tolist(), begins[full + 1].tolist()):
        values[a:b].sort()
    new = np.ones(len(values), bool)
    new[1:] = values[1:] != values[:-1]
    new[begins[:-1][sizes > 0]] = True
    return values[new], np.r_[0, np.cumsum(new)][begins]


def first_names(grams: np.ndarray, begins: np.ndarray, salt: int = 0) -> np.ndarray:
    """A hash of each set; 0 for the empty set alone."""
    sums = np.r_[np.zeros(1, np.uint64), np.cumsum(K.mix(grams ^ np.uint64(salt)))]
    names = K.mix((sums[begins[1:]] - sums[begins[:-1]]) + np.diff(begins).astype(np.uint64))
    names[names == 0] = np.uint64(1)
    names[np.diff(begins) == 0] = np.uint64(0)
    return names


def second_names(grams: np.ndarray, begins: np.ndarray) -> np.ndarray:
    return first_names(grams, begins, 0xA24BAED4963EE407)


def set_names(grams: np.ndarray, begins: np.ndarray, clashes: frozenset[int] = frozenset()) -> np.ndarray:
    """One number for each set: its first name, or the second where the first is one of clashes, which different sets share."""
    names = first_names(grams, begins)
    if clashes:
        shared = np.isin(K.signed(names), np.array(sorted(clashes), np.int64))
        names = np.where(shared, second_names(grams, begins), names)
    return names


def sketches(grams: np.ndarray, begins: np.ndarray) -> list[bytes]:
    """Parities of the counts of each set's grams in bins, eight a byte: a power of two of bins, two a gram or more."""
    sizes = np.diff(begins)
    bins = np.maximum(BINS, 1 << np.ceil(np.log2(np.maximum(sizes, 1) * 2)).astype(np.int64))
    at = np.cumsum(bins) - bins
    owner = np.repeat(np.arange(len(sizes)), sizes)
    place = at[owner] + (K.mix(grams) >> np.uint64(32)).astype(np.int64) % bins[owner]
    packed = np.packbits((np.bincount(place, minlength=int(bins.sum())) & 1).astype(np.uint8), bitorder="little")
    return [packed[a // 8 : (a + b) // 8].tobytes() if s else b"" for a, b, s in zip(at.tolist(), bins.tolist(), sizes.tolist())]


def _opened(column: pa.Array, rows: np.ndarray, width: int) -> np.ndarray:
    """Sketches of one width (bytes) as a matrix of bytes."""
    offsets = np.frombuffer(column.buffers()[1], np.int32)[column.offset :]
    data = np.frombuffer(column.buffers()[2], np.uint8)
    return data[offsets[rows][:, None] + np.arange(width)]


def _folded(sketch: np.ndarray, width: int) -> np.ndarray:
    """Sketches in fewer bins, as whole words: bin numbers are taken modulo a power of two."""
    if sketch.shape[1] != width:
        sketch = np.bitwise_xor.reduce(sketch.reshape(len(sketch), -1, width), axis=1)
    return np.ascontiguousarray(sketch).view(np.uint64)


def _apart(one: np.ndarray, two: np.ndarray) -> np.ndarray:
    """A lower bound of the symmetric difference: a gram of one set alone changes the parity of one bin."""
    return np.bitwise_count(one ^ two).sum(-1, dtype=np.int64)


def _sums(cells: np.ndarray, values: np.ndarray, n: int) -> np.ndarray:
    """Sum modulo 2 ** 64 of the values of each cell, from exact sums of three pieces of their bits."""
    out = np.zeros(n, np.uint64)
    for shift, bits in ((0, 22), (22, 22), (44, 20)):
        piece = ((values >> np.uint64(shift)) & np.uint64((1 << bits) - 1)).astype(np.float64)
        out += np.bincount(cells, piece, n).astype(np.uint64) << np.uint64(shift)
    return out


def signatures(grams: np.ndarray, begins: np.ndarray, num: int) -> tuple[np.ndarray, np.ndarray]:
    """(set, signature) of sets given by their grams."""
    sizes = np.diff(begins)
    owners, out = [], []
    for f, (low, high, k) in enumerate(families(num, int(sizes.max(initial=0)))):
        if k == 0:
            continue  # only equal sets are that similar
        own = np.flatnonzero((sizes >= low) & (sizes <= high))
        if len(own) == 0:
            continue
        blocks, parts, taken, spare = scheme(k, low)
        salt = np.uint64((f + 1) * 0x9E3779B97F4A7C15 % 2**64)
        at = K.ragged(begins[own], sizes[own])
        values = K.mix(grams[at] ^ salt)
        cells = np.repeat(np.arange(len(own)), sizes[own]) * (blocks * parts) + (values >> np.uint64(33)).astype(np.int64) % (blocks * parts)
        sums = _sums(cells, values, len(own) * blocks * parts).reshape(len(own), blocks, parts)
        held = np.bincount(cells, minlength=sums.size).reshape(sums.shape) > 0
        chosen = list(combinations(range(parts), taken))
        bare = np.zeros((len(own), blocks, len(chosen)), bool)
        for c, subset in enumerate(chosen):
            some = held[:, :, subset].any(2)
            bare[:, :, c] = ~some
            i, b = np.nonzero(some)
            tag = (b * len(chosen) + c + 1).astype(np.uint64)
            owners.append(own[i])
            out.append(K.mix(K.mix(sums[:, :, subset].sum(2)[i, b] ^ salt) + tag))
        # Two sets that lack grams of the same spare + 1 subsets or more share a choice from the first of these.
        size = min(CHOICE, spare + 1)
        for i in np.flatnonzero(bare.sum((1, 2)) > spare):
            empty = np.flatnonzero(bare[i])
            choices = np.array(list(combinations(empty[: len(empty) - spare - 1 + size].tolist(), size)), np.uint64)
            mixed = np.full(len(choices), salt)
            for column in choices.T:
                mixed = K.mix(mixed + column + np.uint64(1))
            owners.append(np.full(len(choices), own[i]))
            out.append(mixed)
    return (np.concatenate(owners), np.concatenate(out)) if out else (np.zeros(0, np.int64), np.zeros(0, np.uint64))


def describe(n: int):
    """(id, key, text) rows into (id, key, n_shingles, name, other, sketch), other being the set's second name."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, data, offsets in K.text_chunks(batch.column(2)):
                s, e, firsts = K.words(data, offsets)
                grams, begins = gram_sets(K.word_hashes(data, s, e, True), firsts, n)
                columns = [pa.array(np.diff(begins)), pa.array(K.signed(first_names(grams, begins))), pa.array(K.signed(second_names(grams, begins))), pa.array(sketches(grams, begins), pa.binary())]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), batch.column(1).slice(a, b - a), *columns], names=["id", "key", "n_shingles", "name", "other", "sketch"])

    return run


def _ranks(new: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of runs that begin where new is set: the first row of each row's run, and its length."""
    begin = np.flatnonzero(new)
    run = np.cumsum(new) - 1
    return begin[run], np.diff(np.r_[begin, len(new)])[run]


def _centres(sig: np.ndarray, name: np.ndarray, first: np.ndarray) -> np.ndarray:
    """For rows by signature and name: the set that a crowd's set is compared with. Sets with the same upper six bits
    have one of them, these have the crowd's first, so that no set is everyone's partner."""
    upper = name >> 58
    new = np.r_[True, (sig[1:] != sig[:-1]) | (upper[1:] != upper[:-1])][: len(sig)]
    own = name[_ranks(new)[0]]
    return np.where(own == name, name[first], own)


MARKS = ["sig", "name", "other"]


def sign(n: int, num: int, clashes: frozenset[int]):
    """Texts into (sig, name, other): a signature of a set, other being 0 if this task has a crowd of it, which follows
    with other as the set to compare with; else null."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        sigs: list[np.ndarray] = []
        names: list[np.ndarray] = []

        def out():
            if not sigs:
                return
            sig, name = np.concatenate(sigs).view(np.int64), np.concatenate(names).view(np.int64)
            order = np.argsort(sig)
            count = np.empty(len(sig), np.int64)
            count[order] = _ranks(np.r_[True, sig[order][1:] != sig[order][:-1]][: len(sig)])[1]
            crowd = count > SENT
            yield pa.RecordBatch.from_arrays([pa.array(sig[~crowd]), pa.array(name[~crowd]), pa.nulls(int((~crowd).sum()), pa.int64())], names=MARKS)
            if crowd.any():
                order = np.lexsort((name[crowd], sig[crowd]))
                sig, name = sig[crowd][order], name[crowd][order]
                first, _ = _ranks(np.r_[True, sig[1:] != sig[:-1]])
                sent = np.unique(first)
                yield pa.RecordBatch.from_arrays([pa.array(sig[sent]), pa.array(name[sent]), pa.array(np.zeros(len(sent), np.int64))], names=MARKS)
                yield pa.RecordBatch.from_arrays([pa.array(sig), pa.array(name), pa.array(_centres(sig, name, first))], names=MARKS)
            sigs.clear()
            names.clear()

        for batch in batches:
            for _, _, data, offsets in K.text_chunks(batch.column(0)):
                s, e, firsts = K.words(data, offsets)
                grams, begins = gram_sets(K.word_hashes(data, s, e, True), firsts, n)
                name = set_names(grams, begins, clashes)
                fresh = []
                for i, x in enumerate(name.tolist()):
                    if x and x not in seen:
                        seen.add(x)
                        fresh.append(i)
                fresh = np.array(fresh, np.int64)
                sizes = np.diff(begins)[fresh]
                own, sig = signatures(grams[K.ragged(begins[fresh], sizes)], np.r_[0, np.cumsum(sizes)], num)
                order = np.argsort(own, kind="stable")  # a set's rows stay together, which shuffles compress
                sigs.append(sig[order])
                names.append(name[fresh][own[order]])
                if sum(map(len, sigs)) > GATHERED:
                    yield from out()
        yield from out()

    return run


def _pairs(name: np.ndarray, first: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All pairs within runs of FEW sets or fewer, each once."""
    a, b = [], []
    for size in range(2, FEW + 1):
        begin = np.flatnonzero((first == np.arange(len(name))) & (count == size))
        for i, j in combinations(range(size), 2):
            a.append(name[begin + i])
            b.append(name[begin + j])
    one, two = np.concatenate(a), np.concatenate(b)
    order = np.lexsort((two, one))
    one, two = one[order], two[order]
    new = np.r_[True, (one[1:] != one[:-1]) | (two[1:] != two[:-1])][: len(one)]
    return one[new], two[new]


def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Marks, sorted by sig and name, into (sig, a, b): candidates a, b; sig is that of a crowd, whose sets are all there as b."""
    sig = name = np.zeros(0, np.int64)
    flag = np.zeros(0, bool)

    def rows(s: np.ndarray | None, a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.nulls(len(a), pa.int64()) if s is None else pa.array(s), pa.array(a), pa.array(b)], names=["sig", "a", "b"])

    def settle(sig: np.ndarray, name: np.ndarray, flag: np.ndarray):
        if len(sig) == 0:
            return
        first, count = _ranks(np.r_[True, sig[1:] != sig[:-1]])
        marked = np.zeros(len(sig), bool)
        marked[first[flag]] = True
        marked = marked[first]
        several = marked | (count > 1)
        crowd = (count > FEW) | marked
        if several.any():
            some = ~crowd & several
            begin = np.cumsum(some) - 1
            yield rows(None, *_pairs(name[some], begin[first[some]], count[some]))
        if crowd.any():
            yield rows(sig[crowd], _centres(sig, name, first)[crowd], name[crowd])

    waiting: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    for batch in batches:
        other = batch.column(2)
        value = np.asarray(other.fill_null(0))
        through = value != 0
        s, x = np.asarray(batch.column(0)), np.asarray(batch.column(1))
        if through.any():
            yield rows(s[through], value[through], x[through])
        waiting.append((s[~through], x[~through], np.asarray(other.is_valid())[~through]))
        if sum(len(w[0]) for w in waiting) < HELD:
            continue
        sig, name, flag = (np.concatenate([old, *(w[i] for w in waiting)]) for i, old in enumerate((sig, name, flag)))
        waiting.clear()
        new = np.r_[True, (sig[1:] != sig[:-1]) | (name[1:] != name[:-1])]
        flag = np.maximum.reduceat(flag, np.flatnonzero(new))
        sig, name = sig[new], name[new]
        cut = int(np.searchsorted(sig, sig[-1]))
        if cut == 0 and len(sig) > HELD:  # one signature fills all: it is a crowd, whose first set stays for what follows
            flag[0] = True
            yield from settle(sig, name, flag)
            sig, name, flag = sig[:1], name[:1], flag[:1]
            continue
        yield from settle(sig[:cut], name[:cut], flag[:cut])
        sig, name, flag = sig[cut:], name[cut:], flag[cut:]
    sig, name, flag = (np.concatenate([old, *(w[i] for w in waiting)]) for i, old in enumerate((sig, name, flag)))
    if len(sig):
        new = np.r_[True, (sig[1:] != sig[:-1]) | (name[1:] != name[:-1])]
        flag = np.maximum.reduceat(flag, np.flatnonzero(new))
        yield from settle(sig[new], name[new], flag)


def sift(num: int):
    """(a, b, size_a, size_b, sketch_a, sketch_b) rows into those pairs (a, b) that sizes and sketches allow."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            one, two = np.asarray(batch.column(2)), np.asarray(batch.column(3))
            keep = 100 * np.minimum(one, two) >= num * np.maximum(one, two)
            widths = [np.diff(np.frombuffer(batch.column(c).buffers()[1], np.int32)[batch.column(c).offset :][: batch.num_rows + 1]) for c in (4, 5)]
            for left, right in {*zip(widths[0][keep].tolist(), widths[1][keep].tolist())}:
                rows = np.flatnonzero(keep & (widths[0] == left) & (widths[1] == right))
                width = min(left, right)
                gap = _apart(_folded(_opened(batch.column(4), rows, left), width), _folded(_opened(batch.column(5), rows, right), width))
                keep[rows] = gap <= most_different(one[rows] + two[rows], num)
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(pa.array(keep)), batch.column(1).filter(pa.array(keep))], names=["a", "b"])

    return run


def across(num: int, nearest: bool):
    """(sig, i, j, block, name, component, size, sketch) rows, sorted by sig, i, j, into pairs (a, b) of different
    components that sketches allow; with nearest, only each set's nearest one among them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        group: tuple | None = None

        def out() -> pa.RecordBatch:
            left = [r for r in held if r[0] == group[1]]
            right = [r for r in held if r[0] == group[2]] if group[1] != group[2] else left
            a, b = [], []
            names = [np.array([r[1] for r in x], np.int64) for x in (left, right)]
            kinds = [np.array([r[2] for r in x], np.int64) for x in (left, right)]
            sizes = [np.array([r[3] for r in x], np.int64) for x in (left, right)]
            bins = min((8 * len(r[4]) for r in held), default=0)
            opened = [_folded_list([r[4] for r in x], bins) for x in (left, right)]
            for i in range(len(left)):
                those = np.flatnonzero((kinds[1] != kinds[0][i]) & (100 * np.minimum(sizes[1], sizes[0][i]) >= num * np.maximum(sizes[1], sizes[0][i])))
                if left is right and not nearest:
                    those = those[those > i]
                if len(those):
                    gap = _apart(opened[0][i], opened[1][those]) - most_different(sizes[1][those] + sizes[0][i], num)
                    hit = those[gap <= 0] if not nearest else those[[gap.argmin()]] if gap.min() <= 0 else those[:0]
                    a += [int(names[0][i])] * len(hit)
                    b += names[1][hit].tolist()
            held.clear()
            return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

        for batch in batches:
            for sig, i, j, *row in zip(*(c.to_pylist() for c in batch.columns)):
                if group is not None and group != (sig, i, j):
                    yield out()
                group = (sig, i, j)
                held.append(row)
        if held:
            yield out()

    return run


def _folded_list(packed: list[bytes], bins: int) -> np.ndarray:
    out = np.zeros((len(packed), bins // 64), np.uint64)
    for i, x in enumerate(packed):
        out[i] = _folded(np.frombuffer(x, np.uint8)[None], bins // 8)[0]
    return out


def fetch(n: int, clashes: frozenset[int]):
    """(name, text) rows: each set's text once a task, and only if it is the set's."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for batch in batches:
            for a, b, data, offsets in K.text_chunks(batch.column(1)):
                wanted = np.asarray(batch.column(0))[a:b]
                s, e, firsts = K.words(data, offsets)
                right = K.signed(set_names(*gram_sets(K.word_hashes(data, s, e, True), firsts, n), clashes)) == wanted
                keep = []
                for i, x in enumerate(wanted.tolist()):
                    if right[i] and x not in seen:
                        seen.add(x)
                        keep.append(a + i)
                yield batch.take(pa.array(keep, pa.int64()))

    return run


def link(n: int, num: int):
    """Rows (cluster, i, j, name, text, a, b), sorted by cluster, i, j and text last: the links among each group's
    candidates a, b that a spanning forest needs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group: tuple | None = None
        sets: dict[int, np.ndarray] = {}
        pairs: list[tuple[int, int]] = []

        def out() -> pa.RecordBatch:
            forest, found = Forest(), []
            for a, b in pairs:
                one, two = sets.get(a), sets.get(b)
                if one is None or two is None:
                    raise ValueError("a set's text is missing")
                if forest.root(a) == forest.root(b):
                    continue
                both = np.concatenate([one, two])
                both.sort()
                common = int((both[1:] == both[:-1]).sum())
                if 100 * common >= num * (len(both) - common):
                    forest.join(a, b)
                    found.append((a, b))
            sets.clear()
            pairs.clear()
            return pa.RecordBatch.from_arrays([pa.array([x for x, _ in found], pa.int64()), pa.array([y for _, y in found], pa.int64())], names=["a", "b"])

        for batch in batches:
            meta = list(zip(*(batch.column(c).to_pylist() for c in (0, 1, 2, 3, 5, 6))))
            for lo, _, data, offsets in K.text_chunks(batch.column(4)):
                s, e, firsts = K.words(data, offsets)
                grams, begins = gram_sets(K.word_hashes(data, s, e, True), firsts, n)
                for t in range(len(offsets) - 1):
                    *at, name, a, b = meta[lo + t]
                    if group is not None and group != tuple(at):
                        yield out()
                    group = tuple(at)
                    if name is None:
                        pairs.append((a, b))
                    else:
                        sets[name] = grams[begins[t] : begins[t + 1]].copy()
        if group is not None:
            yield out()

    return run


def verified(docs: DataFrame, sets: DataFrame, pairs: DataFrame, n: int, num: int, clashes: frozenset[int]) -> DataFrame:
    """a, b: the links among pairs that connect what pairs of them connect. docs: row, text; sets: name, row."""
    clusters = components(pairs)
    members = written(clusters.select(F.col("node").alias("name"), F.col("root").alias("cluster")), "members")
    blocks = members.groupBy("cluster").agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("blocks")).withColumnRenamed("cluster", "_c")
    placed = written(members.join(blocks, F.col("cluster") == F.col("_c")).select("name", "cluster", F.pmod(F.xxhash64("name", F.lit(1)), F.col("blocks")).cast("int").alias("block")), "placed")
    one, two = placed.select(F.col("name").alias("_a"), "cluster", F.col("block").alias("_i")), placed.select(F.col("name").alias("_b"), F.col("block").alias("_j"))
    edges = pairs.join(bounded(one), F.col("a") == F.col("_a")).join(bounded(two), F.col("b") == F.col("_b"))
    edges = edges.select("cluster", F.least("_i", "_j").alias("i"), F.greatest("_i", "_j").alias("j"), "a", "b")
    edges = written(edges, "placed-pairs")
    places = edges.select("cluster", "i", "j", F.explode(F.array("a", "b")).alias("name")).distinct()

    needed = placed.select("name").join(sets.select(F.col("name").alias("_n"), "row"), F.col("name") == F.col("_n")).select("name", F.col("row").alias("_row"))
    texts = docs.join(bounded(written(needed, "needed")), F.col("row") == F.col("_row")).select("name", "text").mapInArrow(fetch(n, clashes), "name long, text string")
    dealt = places.withColumnRenamed("name", "_n").join(texts, F.col("_n") == F.col("name")).select("cluster", "i", "j", "name", "text")
    rows = dealt.withColumns({"a": F.lit(None).cast("long"), "b": F.lit(None).cast("long")}).unionByName(edges.withColumns({"name": F.lit(None).cast("long"), "text": F.lit(None).cast("string")}))
    # Sets come before the pairs of their group; links of one group need no other's.
    return rows.repartition("cluster", "i", "j").sortWithinPartitions("cluster", "i", "j", F.col("a").asc_nulls_first()).select("cluster", "i", "j", "name", "text", "a", "b").mapInArrow(link(n, num), "a long, b long")


def sifted(pairs: DataFrame, sets: DataFrame, num: int) -> DataFrame:
    """Pairs a, b that the sketches of sets allow."""
    side = lambda c: bounded(sets.select(F.col("name").alias(f"_{c}"), F.col("n_shingles").alias(f"size_{c}"), F.col("sketch").alias(f"sketch_{c}")), 50_000)
    both = pairs.join(side("a"), F.col("a") == F.col("_a")).join(side("b"), F.col("b") == F.col("_b"))
    return both.select("a", "b", "size_a", "size_b", "sketch_a", "sketch_b").mapInArrow(sift(num), "a long, b long")


def remaining(crowds: DataFrame, roots: DataFrame, sets: DataFrame, num: int, nearest: bool) -> DataFrame:
    """Pairs that share a crowd, are of different components and pass their sketches: all, or each set's nearest in its
    block and crowd. crowds: sig, name; roots: node, root."""
    named = crowds.join(bounded(roots.withColumnRenamed("node", "_n")), F.col("name") == F.col("_n"), "left").select("sig", "name", F.coalesce("root", "name").alias("component"))
    open_ = named.groupBy("sig").agg(F.count(F.lit(1)).alias("n"), F.min("component").alias("low"), F.max("component").alias("high")).where(F.col("low") != F.col("high"))
    open_ = open_.select(F.col("sig").alias("_s"), F.ceil(F.col("n") / BLOCK).cast("int").alias("blocks"))
    rows = named.join(open_, F.col("sig") == F.col("_s")).withColumn("block", F.pmod(F.xxhash64("name", F.lit(1)), F.col("blocks")).cast("int"))
    rows = written(rows.select("sig", "name", "component", "block", "blocks"), "open")
    known = rows.join(sets.select(F.col("name").alias("_n"), "n_shingles", "sketch"), F.col("name") == F.col("_n"))
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    dealt = known.withColumn("_o", other).select("sig", F.least("block", "_o").alias("i"), F.greatest("block", "_o").alias("j"), "block", "name", "component", "n_shingles", "sketch")
    return dealt.repartition("sig", "i", "j").sortWithinPartitions("sig", "i", "j").mapInArrow(across(num, nearest), "a long, b long").distinct()


def near_duplicates(df: DataFrame, id: str = "doc_id", text: str = "text", n: int = 5, num: int = 80) -> DataFrame:
    """id, key, n_shingles, name (of its set; 0: none), component: the least id that links reach, and group: one number
    for all rows of a component (null without a set). One row for each row.

    Words are runs outside white space, A-Z lower-cased; a text of fewer than n words has one gram, of all its words.
    Edge cases: null, empty and blank texts have no set and are linked with nothing; equal sets are one set with all
    their rows; repeated rows share a component; other columns are not read; an empty table gives an empty result. Rows
    with a null id take part in links and have the least id of their component, null if none has one. Sets are known by
    64 bits, confirmed by another 64: where different sets share the first, the second is used.
    """
    docs = df.select(F.col(id).cast("long").alias("id"), F.coalesce(F.col(text), F.lit("")).alias("text")).withColumn("key", F.xxhash64("text"))
    rows = written(docs.select("id", "key", "text").mapInArrow(describe(n), "id long, key long, n_shingles long, name long, other long, sketch binary"), "sets")
    twice = rows.groupBy("name").agg(F.min("other").alias("low"), F.max("other").alias("high")).where(F.col("low") != F.col("high"))
    clashes = frozenset(r["name"] for r in twice.select("name").collect())  # one in 2 ** 64 pairs of sets
    if clashes:
        rows = rows.withColumn("name", F.when(F.col("name").isin(*clashes), F.col("other")).otherwise(F.col("name")))
    row = F.xxhash64("id", "key")
    sets = written(rows.where(F.col("name") != 0).groupBy("name").agg(F.min("id").alias("least_id"), F.min(row).alias("row"), F.first("n_shingles").alias("n_shingles"), F.first("sketch").alias("sketch")), "distinct-sets")

    marks = docs.select("text").mapInArrow(sign(n, num, clashes), "sig long, name long, other long")
    to = F.when(F.coalesce("other", F.lit(0)) == 0, F.col("sig")).otherwise(F.col("name"))
    met = written(marks.repartition(to).sortWithinPartitions("sig", "name").mapInArrow(meet, "sig long, a long, b long"), "candidates")
    pairs = written(sifted(met.where(F.col("a") != F.col("b")).select("a", "b").distinct(), sets, num), "sifted")
    own = docs.select(row.alias("row"), "text")
    links = written(verified(own, sets, pairs, n, num, clashes), "links")
    roots = components(links)

    crowds = met.where(F.col("sig").isNotNull()).select("sig", F.col("b").alias("name")).distinct()
    for nearest in (True, False):  # what the nearest pairs join need not be compared in all pairs
        more = written(remaining(crowds, roots, sets, num, nearest), "remaining")
        if more.isEmpty():
            break
        links = written(links.unionByName(verified(own, sets, more, n, num, clashes)), "links")
        roots = components(links)

    owned = written(sets.join(roots.withColumnRenamed("node", "_n"), F.col("name") == F.col("_n"), "left").select("name", "least_id", F.coalesce("root", "name").alias("root")), "owned")
    least = owned.groupBy("root").agg(F.min("least_id").alias("component")).withColumnRenamed("root", "_r")
    named = owned.join(least, F.col("root") == F.col("_r")).select(F.col("name").alias("_n"), "component", F.col("root").alias("group"))
    out = rows.join(named, F.col("name") == F.col("_n"), "left")
    return out.select("id", "key", "n_shingles", "name", F.when(F.col("name") == 0, F.col("id")).otherwise(F.col("component")).alias("component"), "group")
