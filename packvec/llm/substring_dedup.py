"""Operator 10: words inside repeated windows are removed, by super-k-mer partitioning.

A window is WINDOW consecutive words; its minimiser is the least hash of the MINIMISER-word grams inside it. Consecutive
windows that share a minimiser form a super-k-mer. Equal windows have equal minimisers, so:

1. minimisers are counted, and only those with two or more places, or with a place that may repeat inside itself, go on;
2. a text's super-k-mers with such minimisers travel as packed strings of words to the minimiser's bucket, where their
   windows are sorted by hash and compared word by word;
3. a minimiser with more than HEAVY places (a passage that very many texts share) would fill one task, so each task
   compares its own windows of it by words, marks those it has twice, and sends the hash of one place of each distinct
   window on; only windows whose hash another task has too travel as packed strings, to the bucket of that hash, where
   they are compared by words as in 2. So a window is sent once a task at most, however many texts share it;
4. the repeated windows come back to their texts.

Equal texts have one key and are one text with a count; if it is over 1, all their windows are repeated. Keys are 64
bits of the text, confirmed by 64 others: where different texts share the first, the second is used.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from packvec.llm import text_kernel as K
from packvec.llm.common import bounded, written

WINDOW, MINIMISER, HEAVY = 35, 8, 2_000
#: Windows of a super-k-mer at most, and rows of a bucket that are sorted at once (a bucket has HEAVY rows at most).
LONGEST, AT_ONCE = 256, 20_000
#: Windows of heavy minimisers that a task compares at once.
HELD = 200_000


def sliding_minimum(x: np.ndarray, n: int) -> np.ndarray:
    """Least of each n consecutive entries, by doubling."""
    width = 1
    while width * 2 <= n:
        x = np.minimum(x[:-width], x[width:])
        width *= 2
    return np.minimum(x[: len(x) - (n - width)], x[n - width :]) if n > width else x


def super_kmers(hashes: np.ndarray, firsts: np.ndarray, window: int, minimiser: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(text, minimiser, first window, windows) of the super-k-mers of texts whose words begin at firsts (one more at the end)."""
    none = np.zeros(0, np.int64)
    if len(hashes) < window:
        return none, none.astype(np.uint64), none, none
    least = sliding_minimum(K.gram_hashes(hashes, minimiser), window - minimiser + 1)
    counts = np.maximum(np.diff(firsts) - window + 1, 0)
    at = K.ragged(firsts[:-1], counts)
    if len(at) == 0:
        return none, none.astype(np.uint64), none, none
    text = np.repeat(np.arange(len(counts)), counts)
    value, inside = least[at], at - firsts[text]
    new = np.ones(len(at), bool)
    new[1:] = (value[1:] != value[:-1]) | (text[1:] != text[:-1])
    begin = np.flatnonzero(new)
    run = np.arange(len(at)) - np.repeat(begin, np.diff(np.r_[begin, len(at)]))
    begin = np.flatnonzero(run % LONGEST == 0)
    return text[begin], value[begin], inside[begin], np.diff(np.r_[begin, len(at)])


def repeats_inside(hashes: np.ndarray, firsts: np.ndarray, text: np.ndarray, value: np.ndarray, start: np.ndarray, n: np.ndarray, window: int, minimiser: int) -> np.ndarray:
    """Whether a super-k-mer's minimiser stands in it twice or more, as it does wherever two of its windows are equal."""
    out = np.zeros(len(n), bool)
    several = np.flatnonzero(n > 1)
    if len(several) == 0:
        return out
    grams = n[several] + window - minimiser
    at = K.ragged(firsts[text[several]] + start[several], grams)
    same = K.gram_hashes(hashes, minimiser)[at] == np.repeat(value[several], grams)
    out[several] = np.add.reduceat(same, np.cumsum(grams) - grams, dtype=np.int64) > 1
    return out


def occurrence(keys: np.ndarray, starts: np.ndarray) -> np.ndarray:
    return K.mix(keys.view(np.uint64) * np.uint64(K._BASE) + starts.astype(np.uint64))


def _texts(batch: pa.RecordBatch, keys: int, texts: int):
    """Chunks of a batch: first row, keys, words and the hashes of words."""
    all_keys = np.asarray(batch.column(keys), np.int64)
    for a, b, data, offsets in K.text_chunks(batch.column(texts)):
        s, e, firsts = K.words(data, offsets)
        yield a, all_keys[a:b], data, s, e, firsts, K.word_hashes(data, s, e)


def find(window: int, minimiser: int):
    """(key, text) rows into (mini, occ, key, start, n, inside), each key once a task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for batch in batches:
            for _, keys, _, _, _, firsts, hashes in _texts(batch, 0, 1):
                text, value, start, n = super_kmers(hashes, firsts, window, minimiser)
                fresh = np.zeros(len(keys), bool)
                for i, k in enumerate(keys.tolist()):
                    if k not in seen:
                        seen.add(k)
                        fresh[i] = True
                keep = fresh[text]
                text, value, start, n = text[keep], value[keep], start[keep], n[keep]
                inside = repeats_inside(hashes, firsts, text, value, start, n, window, minimiser)
                yield pa.RecordBatch.from_arrays([pa.array(K.signed(value)), pa.array(K.signed(occurrence(keys[text], start))), pa.array(keys[text]), pa.array(start.astype(np.int32)), pa.array(n.astype(np.int32)), pa.array(inside)], names=["mini", "occ", "key", "start", "n", "inside"])

    return run


def _each(batches: Iterator[pa.RecordBatch], heavy: bool):
    """(doc, key, text, places) rows, each key once a task, as chunks: words, their hashes, and (text, minimiser, first word, first window, windows) of places of one kind."""
    seen: set[int] = set()
    for batch in batches:
        places = batch.column(3)
        offsets, parts = np.asarray(places.offsets, np.int64), places.flatten()
        minis, starts, counts, kinds = (np.asarray(parts.field(c).to_numpy(zero_copy_only=False)) for c in ("mini", "start", "n", "heavy"))
        offsets = offsets - offsets[0]
        for a, keys, data, s, e, firsts, hashes in _texts(batch, 1, 2):
            found = []
            for i, k in enumerate(keys.tolist()):
                if k in seen:
                    continue
                seen.add(k)
                for p in range(offsets[a + i], offsets[a + i + 1]):
                    if bool(kinds[p]) == heavy:
                        found.append((k, int(minis[p]), int(firsts[i] + starts[p]), int(starts[p]), int(counts[p])))
            if found:
                yield data, s, e, hashes, found


def _strings(data: np.ndarray, s: np.ndarray, e: np.ndarray, found: list[tuple], window: int) -> list[bytes]:
    """The words of places, joined by one space."""
    return [b" ".join(data[s[first] : e[first + n + window - 2]].tobytes().split()) for _, _, first, _, n in found]


def pack(window: int):
    """Packed super-k-mers of ordinary minimisers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for data, s, e, _, found in _each(batches, False):
            rows = [(mini, k, start, n, x) for (k, mini, _, start, n), x in zip(found, _strings(data, s, e, found, window))]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary()))], names=["mini", "key", "start", "n", "packed"])

    return run


PLACES = "mini long, key long, start int, n int"


def _marks(key: np.ndarray, start: np.ndarray) -> pa.RecordBatch:
    """Marks of distinct places, consecutive ones joined."""
    order = np.lexsort((start, key))
    key, start = key[order], start[order]
    new = np.r_[True, (key[1:] != key[:-1]) | (start[1:] != start[:-1] + 1)][: len(key)]
    begin = np.flatnonzero(new)
    return pa.RecordBatch.from_arrays([pa.nulls(len(begin), pa.int64()), pa.array(key[begin]), pa.array(start[begin].astype(np.int32)), pa.array(np.diff(np.r_[begin, len(key)]).astype(np.int32))], names=["mini", "key", "start", "n"])


def sift(window: int, held: int = HELD):
    """Places of heavy minimisers into marks (without mini) of windows that this task has twice, and one place of each
    distinct window under its hash."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts: list[tuple[int, int, int, bytes]] = []

        def out() -> Iterator[pa.RecordBatch]:
            keys, starts, counts, packed = zip(*parts)
            parts.clear()
            key, start, at, kind = window_classes(np.array(keys, np.int64), np.array(starts, np.int64), np.array(counts, np.int64), packed, window)
            again = np.bincount(kind)[kind] > 1
            yield _marks(key[again], start[again])
            data = np.frombuffer(b"".join(packed), np.uint8)
            s, e, _ = K.words(data, np.cumsum([0, *map(len, packed)]))
            one = np.r_[True, kind[1:] != kind[:-1]]
            named = K.signed(K.gram_hashes(K.word_hashes(data, s, e), window)[at[one]])
            yield pa.RecordBatch.from_arrays([pa.array(named), pa.array(key[one]), pa.array(start[one].astype(np.int32)), pa.array(np.ones(one.sum(), np.int32))], names=["mini", "key", "start", "n"])

        windows = 0
        for data, s, e, _, found in _each(batches, True):
            for (k, _, _, start, n), x in zip(found, _strings(data, s, e, found, window)):
                parts.append((k, start, n, x))
                windows += n
                if windows >= held:
                    yield from out()
                    windows = 0
        if parts:
            yield from out()

    return run


def twins(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Places sorted by hash into those whose hash another place has."""
    last: pa.RecordBatch | None = None  # the last place so far, and whether it went out
    gone = False
    for batch in batches:
        if batch.num_rows == 0:
            continue
        # Built anew each time: batches that go out must share one schema, whatever nulls the input declares.
        columns = batch.columns if last is None else [pa.concat_arrays([x, y]) for x, y in zip(last.columns, batch.columns)]
        batch = pa.RecordBatch.from_arrays(columns, names=["mini", "key", "start", "n"])
        h = batch.column(0).to_numpy()
        same = h[1:] == h[:-1]
        hit = np.r_[False, same] | np.r_[same, False]
        # The last place's like may follow in the next batch; the first was sent before if it had one.
        send = hit.copy()
        if last is not None and gone:
            send[0] = False
        yield batch.filter(pa.array(send))
        gone = bool(hit[-1]) or (len(h) == 1 and gone)
        last = batch.slice(batch.num_rows - 1)


def window_classes(keys: np.ndarray, starts: np.ndarray, counts: np.ndarray, packed: list[bytes], window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(key, start, first word, class) of the distinct windows of these super-k-mers, sorted by class; a class is one sequence of words."""
    names: dict[bytes, int] = {}
    ids = np.array([names.setdefault(w, len(names)) for p in packed for w in p.split(b" ")], np.int64)
    firsts = np.cumsum(counts + window - 1) - (counts + window - 1)
    at = K.ragged(firsts, counts)
    key, start = np.repeat(keys, counts), K.ragged(starts, counts)
    hashes = K.gram_hashes(K.mix(ids.astype(np.uint64) + np.uint64(1)), window)[at]
    order = np.lexsort((start, key, hashes))
    at, key, start, hashes = at[order], key[order], start[order], hashes[order]
    other = np.r_[True, (hashes[1:] != hashes[:-1]) | (key[1:] != key[:-1]) | (start[1:] != start[:-1])][: len(at)]
    at, key, start, hashes = at[other], key[other], start[other], hashes[other]
    kind = np.cumsum(np.r_[False, hashes[1:] != hashes[:-1]][: len(at)])
    near = np.flatnonzero(hashes[1:] == hashes[:-1])
    for i in range(0, len(near), 50_000):  # equal hashes are taken at their word only after the words agree
        p = near[i : i + 50_000]
        if not (ids[at[p][:, None] + np.arange(window)] == ids[at[p + 1][:, None] + np.arange(window)]).all():
            found: dict[bytes, int] = {}
            kind = np.array([found.setdefault(ids[a : a + window].tobytes(), len(found)) for a in at], np.int64)
            order = np.argsort(kind, kind="stable")
            return key[order], start[order], at[order], kind[order]
    return key, start, at, kind


def repeated_windows(keys: np.ndarray, starts: np.ndarray, counts: np.ndarray, packed: list[bytes], window: int) -> tuple[np.ndarray, np.ndarray]:
    """(key, start) of windows whose words also stand at another (key, start) of these super-k-mers."""
    key, start, _, kind = window_classes(keys, starts, counts, packed, window)
    hit = np.bincount(kind)[kind] > 1
    return key[hit], start[hit]


def compare(window: int):
    """Packed super-k-mers, sorted by minimiser, into marks of repeated windows; whole buckets at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def out(t: pa.Table):
            column = lambda c: t.column(c).to_numpy()
            key, start = repeated_windows(column("key"), column("start").astype(np.int64), column("n").astype(np.int64), t.column("packed").to_pylist(), window)
            return _marks(key, start)

        for batch in batches:
            held.append(batch)
            if sum(b.num_rows for b in held) >= AT_ONCE:
                t = pa.Table.from_batches(held)
                minis = t.column("mini").to_numpy()
                cut = int(np.searchsorted(minis, minis[-1], "left"))
                if cut:
                    yield out(t.slice(0, cut))
                    held = t.slice(cut).combine_chunks().to_batches()
        if held:
            yield out(pa.Table.from_batches(held))

    return run


def finish(window: int, whole: bool):
    """(id, text, copies, marks) rows into id, n_words, n_removed, kept digest and, with whole, the kept text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n_words, n_removed, digests, texts = [], [], [], []
            for text, copies, marks in zip(batch.column(1), batch.column(2), batch.column(3)):
                words = (text.as_py() or "").encode().split()
                kept, marks = words, marks.as_py()
                if copies.as_py() > 1 and len(words) >= window:
                    kept = []
                elif marks:
                    gone = np.zeros(len(words) + 1, np.int32)
                    first = np.array([m["start"] for m in marks])
                    np.add.at(gone, first, 1)
                    np.add.at(gone, first + np.array([m["n"] for m in marks]) + window - 1, -1)
                    kept = [w for w, g in zip(words, np.cumsum(gone[:-1]).tolist()) if not g]
                line = b" ".join(kept)
                n_words.append(len(words))
                n_removed.append(len(words) - len(kept))
                digests.append(hashlib.sha256(line).hexdigest())
                if whole:
                    texts.append(line.decode())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(digests, pa.string()), *([pa.array(texts, pa.string())] if whole else [])], names=["id", "n_words", "n_removed", "kept_sha256", *(["kept"] if whole else [])])

    return run


def remove_repeats(df: DataFrame, id: str = "doc_id", text: str = "text", window: int = WINDOW, minimiser: int = MINIMISER, heavy: int = HEAVY, whole: bool = False) -> DataFrame:
    """id, n_words, n_removed, kept_sha256 of every row, and with whole the kept words, joined by one space.

    Edge cases: null and empty texts have no words; texts shorter than a window keep all; repeated rows are copies of
    each other, whose windows are all repeated; ids may repeat or be null; other columns are not read; an empty table
    gives an empty result. heavy decides only how windows are dealt to tasks, never which are repeated.
    """
    docs = df.select(F.col(id).alias("id"), F.coalesce(F.col(text), F.lit("")).alias("text")).withColumn("key", F.xxhash64("text"))
    other = F.xxhash64(F.lit(1), "text")
    copies = docs.groupBy("key").agg(F.count(F.lit(1)).alias("copies"), F.min(other).alias("low"), F.max(other).alias("high"))
    copies = written(copies.where("copies > 1"), "copies")
    clashes = [r["key"] for r in copies.where("low != high").select("key").collect()]  # one in 2 ** 64 pairs of texts
    if clashes:
        docs = docs.withColumn("key", F.when(F.col("key").isin(*clashes), other).otherwise(F.col("key")))
        copies = docs.groupBy("key").agg(F.count(F.lit(1)).alias("copies")).where("copies > 1")
    places = docs.select("key", "text").mapInArrow(find(window, minimiser), "mini long, occ long, key long, start int, n int, inside boolean")
    counted = places.groupBy("mini").agg(F.min("occ").alias("low"), F.max("occ").alias("high"), F.count(F.lit(1)).alias("places"), F.max("inside").alias("inside"))
    shared = counted.where((F.col("low") != F.col("high")) | F.col("inside")).select(F.col("mini").alias("_mini"), (F.col("places") > heavy).alias("heavy"))
    gathered = lambda x: x.groupBy("key").agg(F.collect_set(F.struct("mini", "start", "n", "heavy")).alias("places")).withColumnRenamed("key", "_key")
    kept = written(gathered(places.join(shared, F.col("mini") == F.col("_mini"))), "kept")

    of = lambda x: docs.select("id", "key", "text").join(x, F.col("key") == F.col("_key")).select("id", "key", "text", "places")
    texts = of(kept)
    has = lambda kind: texts.where(F.exists("places", lambda p: p["heavy"] == F.lit(kind)))
    strings = lambda x: x.mapInArrow(pack(window), "mini long, key long, start int, n int, packed binary")
    sifted = written(has(True).mapInArrow(sift(window), PLACES), "sifted")
    met = sifted.where(F.col("mini").isNotNull()).repartition("mini").sortWithinPartitions("mini").mapInArrow(twins, PLACES)
    again = written(gathered(met.withColumn("heavy", F.lit(False))), "twins")
    packed = strings(has(False)).unionByName(strings(of(bounded(again))))
    by_bucket = packed.repartition("mini").sortWithinPartitions("mini").mapInArrow(compare(window), PLACES)
    marks = by_bucket.unionByName(sifted.where(F.col("mini").isNull())).groupBy("key").agg(F.collect_set(F.struct("start", "n")).alias("marks"))
    known = copies.select("key", "copies").join(marks, "key", "full").select(F.col("key").alias("_key"), "copies", "marks")
    judged = docs.select("id", "key", "text").join(known, F.col("key") == F.col("_key"), "left").select("id", "text", F.coalesce("copies", F.lit(1)).cast("long").alias("copies"), "marks")
    kind = df.schema[id].dataType.simpleString()
    out = judged.mapInArrow(finish(window, whole), f"id {kind}, n_words long, n_removed long, kept_sha256 string" + ", kept string" * whole)
    return out.withColumnRenamed("id", id)
