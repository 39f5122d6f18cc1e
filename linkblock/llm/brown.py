"""Class-based bigram language model with exchange clustering.

Every training word is counted, in Spark. The most frequent words (the head)
are assigned to classes by exchange: each word in turn moves to the class
where the likelihood of class bigrams is greatest. Every other word seen LEAST
times or more then goes, in a distributed pass, to the class where the
likelihood gains most by its neighbours in the head; transitions are counted
anew over all words. The number of classes grows with the cube root of the
number of such words. Words seen less often form one open class, the end of a
text another. A word costs the transition from the class before it times its
emission from its own class.

Texts are read twice: once to count words, once to turn them into numbers,
which are written and serve all later passes. What travels to the workers is
bounded: the KNOWN most frequent words and a class for each. An occurrence of
any other word is a row of its own, dealt by word, so that its class and exact
count are found where all its occurrences meet, and dealt again by text.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from linkblock.llm.common import LOWER, as_bytes, narrow, written
from linkblock.runtime import settle

CLUSTERED, CLASSES, KNOWN, SWEEPS = 1000, 32, 400_000, 6
#: Words seen so often have a class; for each class the head holds so many words at least.
LEAST, HEAD = 2, 8
#: However large the corpus, a model has at most so many classes (a table of transitions has their square).
MOST_CLASSES = 512
#: Gains of neighbour counts up to this are looked up instead of computed.
SMALL = 16
#: Weight of the class's own share against the transitions seen from the class before.
PRIOR = 20.0
#: The end of a text, which no word can equal.
END = b" "


def held_out(id_col: Column) -> Column:
    return F.coalesce(F.crc32(id_col.cast("string").cast("binary")) % 7 == 2, F.lit(False))


def word_counts(texts: DataFrame) -> DataFrame:
    """(word binary, c): every word and END, over texts given as bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            seen: Counter = Counter()
            for text in b.column("text").to_pylist():
                seen.update(text.translate(LOWER).split())
            seen[END] = b.num_rows
            yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.binary()), pa.array(list(seen.values()), pa.int64())], names=["word", "c"])

    return texts.mapInArrow(run, "word binary, c bigint").groupBy("word").agg(F.sum("c").alias("c")).where("c > 0")


def least_count(words: DataFrame, most: int) -> int:
    """The least count that at most `most` words reach, from the table of how many words have each count.

    No task sorts words; what is summed in order has a row for each distinct count.
    """
    table = words.groupBy("c").agg(F.count("*").alias("n"))
    run = table.select("c", F.sum("n").over(Window.partitionBy(F.lit(0)).orderBy(F.desc("c"))).alias("reach"))
    found = run.where(F.col("reach") <= most).agg(F.min("c").alias("c")).first()["c"]
    return found if found is not None else (1 << 62)


def encode(texts: DataFrame, words: list[bytes]) -> DataFrame:
    """texts (doc_id, held_out, text) as numbers: key (one a row), doc_id, held_out, ids, strange.

    ids: the compressed places of its words in `words`, -1 for any other word;
    strange: those other words in order, with blanks between.
    """
    end = len(words)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index, packer = {w: i for i, w in enumerate(words)}, zstandard.ZstdCompressor(level=1)
        for whole in batches:
            for at in range(0, whole.num_rows, 512):
                part, ids, strange = whole.slice(at, 512), [], []
                for text in part.column("text").to_pylist():
                    tokens = text.translate(LOWER).split()
                    own = [index.get(w, -1) for w in tokens]
                    own.append(end)
                    ids.append(packer.compress(np.array(own, np.int32).tobytes()))
                    strange.append(b" ".join([w for w, i in zip(tokens, own, strict=False) if i < 0]))
                yield pa.RecordBatch.from_arrays([part.column("key"), part.column("doc_id"), part.column("held_out"), pa.array(ids, pa.binary()), pa.array(strange, pa.binary())], names=["key", "doc_id", "held_out", "ids", "strange"])

    keyed = texts.select(F.monotonically_increasing_id().alias("key"), "doc_id", "held_out", "text")
    return written(keyed.mapInArrow(run, "key bigint, doc_id bigint, held_out boolean, ids binary, strange binary"))


def _slices(batches: Iterator[pa.RecordBatch], rows: int = 1024) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Of encoded rows: (the rows, all their ids in a row with an end after each text, where each text starts)."""
    unpack = zstandard.ZstdDecompressor().decompress
    for whole in batches:
        for at in range(0, whole.num_rows, rows):
            part = whole.slice(at, rows)
            ids = [np.frombuffer(unpack(x), np.int32) for x in part.column("ids").to_pylist()]
            lengths = np.array([len(x) for x in ids], np.int64)
            yield part, np.concatenate(ids).astype(np.int64), np.cumsum(lengths) - lengths


def _before(of: np.ndarray, end: int) -> np.ndarray:
    """What stands before each token: the end before the first."""
    return np.r_[end, of[:-1]]


def _summed(cells: DataFrame, size: int) -> np.ndarray:
    """Rows (cell, n) as a square matrix of sums: at most size * size rows meet the driver, whatever the corpus."""
    found = cells.groupBy("cell").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(size * size, np.int64)
    out[found.column("cell").to_numpy()] = found.column("n").to_numpy()
    return out.reshape(size, size)


def pair_cells(encoded: DataFrame, of: np.ndarray, kinds: int) -> DataFrame:
    """(cell, n): neighbouring tokens by kind (of: a kind for each id); pairs with a token of kind -1 are left out."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells = np.zeros(kinds * kinds, np.int64)
        for _, ids, _ in _slices(batches):
            now = of[ids]
            was = _before(now, of[-2])
            both = (now >= 0) & (was >= 0)
            cells += np.bincount(was[both] * kinds + now[both], minlength=kinds * kinds)
        used = np.flatnonzero(cells)
        yield pa.RecordBatch.from_arrays([pa.array(used), pa.array(cells[used])], names=["cell", "n"])

    return encoded.mapInArrow(run, "cell bigint, n bigint")


def _phi(x: np.ndarray) -> np.ndarray:
    return np.where(x > 0, x * np.log(np.maximum(x, 1)), 0.0)


def exchange(pairs: np.ndarray, movable: int, classes: int = CLASSES, sweeps: int = SWEEPS) -> np.ndarray:
    """Class of every row of pairs. Rows from `movable` on keep classes of their own, the last ones."""
    pairs = pairs.astype(np.float64)
    size = len(pairs)
    kinds = classes + size - movable
    of = np.r_[np.arange(movable) % classes, np.arange(classes, kinds)]
    after = np.zeros((size, kinds))
    before = np.zeros((size, kinds))
    for c in range(kinds):
        after[:, c] = pairs[:, of == c].sum(axis=1)
        before[:, c] = pairs[of == c].sum(axis=0)
    table = np.stack([after[of == c].sum(axis=0) for c in range(kinds)])
    left, right = pairs.sum(axis=1), pairs.sum(axis=0)
    out, into = table.sum(axis=1), table.sum(axis=0)
    own = np.arange(classes)
    for _ in range(sweeps):
        moved = 0
        for w in range(movable):
            a, s = of[w], pairs[w, w]
            nxt, prv = after[w].copy(), before[w].copy()
            nxt[a] -= s
            prv[a] -= s
            table[a] -= nxt
            table[:, a] -= prv
            table[a, a] -= s
            out[a] -= left[w]
            into[a] -= right[w]
            rows, cols = table[own], table[:, own].T
            gain = (_phi(rows + nxt) - _phi(rows)).sum(axis=1) + (_phi(cols + prv) - _phi(cols)).sum(axis=1)
            diagonal = table[own, own]
            gain += _phi(diagonal + nxt[own] + prv[own] + s) - _phi(diagonal + nxt[own]) - _phi(diagonal + prv[own]) + _phi(diagonal)
            gain -= _phi(out[own] + left[w]) - _phi(out[own]) + _phi(into[own] + right[w]) - _phi(into[own])
            b = int(gain.argmax()) if gain.max() > gain[a] + 1e-9 else a
            table[b] += nxt
            table[:, b] += prv
            table[b, b] += s
            out[b] += left[w]
            into[b] += right[w]
            if b != a:
                of[w], moved = b, moved + 1
                after[:, a] -= pairs[:, w]
                after[:, b] += pairs[:, w]
                before[:, a] -= pairs[w]
                before[:, b] += pairs[w]
        if not moved:
            break
    return of


def class_chooser(table: np.ndarray, classes: int) -> Callable[[np.ndarray, np.ndarray], np.ndarray]:
    """A function from counts of words by slot (rows; slots: kind after, then kind before) and times to classes of greatest gain.

    The gain is that of exchange(), against the table of the head's classes.
    """
    base = np.r_[table[:classes].T, table[:, :classes]].astype(np.float64)  # by slot: counts of each class with the neighbour
    out, into = table.sum(axis=1)[:classes].astype(np.float64), table.sum(axis=0)[:classes].astype(np.float64)
    small = np.stack([_phi(base + n) - _phi(base) for n in range(SMALL + 1)])

    def choose(counts: np.ndarray, times: np.ndarray) -> np.ndarray:
        best = np.zeros(len(counts), np.int64)
        for a in range(0, len(counts), 128):
            word, slot = np.nonzero(counts[a : a + 128])
            n = counts[a + word, slot]
            gain = small[np.minimum(n, SMALL), slot]
            big = np.flatnonzero(n > SMALL)
            gain[big] = _phi(base[slot[big]] + n[big, None]) - _phi(base[slot[big]])
            c = times[a : a + 128, None]
            total = np.zeros((len(c), classes))
            if len(word):
                starts = np.flatnonzero(np.r_[True, word[1:] != word[:-1]])
                total[word[starts]] = np.add.reduceat(gain, starts)
            best[a : a + 128] = (total - _phi(out + c) + _phi(out) - _phi(into + c) + _phi(into)).argmax(axis=1)
        return best

    return choose


def _slots(now: np.ndarray, kinds: int, end: int) -> tuple[np.ndarray, np.ndarray]:
    """For each token the slot of the kind after it and of the kind before it. An end is never asked."""
    return np.r_[now[1:], end], kinds + _before(now, end)


def known_classes(encoded: DataFrame, of: np.ndarray, head: int, table: np.ndarray, classes: int, least: int = LEAST) -> tuple[np.ndarray, np.ndarray]:
    """(ids, classes) of the known words outside the head that are seen `least` times or more.

    of: a kind for each id. A row is a word of a slice of texts with the slots
    of all its neighbours; where a word's rows meet, one vector of counts is
    held at a time. At most KNOWN rows meet the driver.
    """
    kinds, known = len(table), len(of) - 2

    def scatter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, ids, _ in _slices(batches, 4096):
            after, before = _slots(of[ids], kinds, kinds - 1)
            at = np.flatnonzero((ids >= head) & (ids < known))
            at = at[np.argsort(ids[at], kind="stable")]
            starts = np.flatnonzero(np.r_[True, ids[at[1:]] != ids[at[:-1]]]) if len(at) else at
            flat = np.stack([after[at], before[at]], axis=1).astype(np.uint16)
            slots = pa.BinaryArray.from_buffers(pa.binary(), len(starts), [None, pa.py_buffer(np.r_[starts, len(at)].astype(np.int32) * np.int32(4)), pa.py_buffer(flat.tobytes())])
            yield pa.RecordBatch.from_arrays([pa.array(ids[at[starts]].astype(np.int32)), slots], names=["id", "slots"])

    choose = class_chooser(table, classes)

    def decide(ids: np.ndarray, counts: np.ndarray) -> pa.RecordBatch:
        times = counts[:, :kinds].sum(axis=1)
        kept = times >= least
        return pa.RecordBatch.from_arrays([pa.array(ids[kept].astype(np.int32)), pa.array(choose(counts[kept], times[kept]).astype(np.int16))], names=["id", "class"])

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, held = -1, np.zeros(2 * kinds, np.int64)
        for whole in batches:
            for at in range(0, whole.num_rows, 1024):
                part = whole.slice(at, 1024)
                ids, slots = part.column("id").to_numpy(), [np.frombuffer(x.as_buffer(), np.uint16) for x in part.column("slots")]
                own, place = np.unique(ids, return_inverse=True)
                row = np.repeat(place, [len(x) for x in slots])
                counts = np.bincount(row * 2 * kinds + np.concatenate(slots), minlength=len(own) * 2 * kinds).reshape(len(own), -1)
                if own[0] == last:
                    counts[0] += held
                elif last >= 0:
                    yield decide(np.array([last]), held[None])
                yield decide(own[:-1], counts[:-1])
                last, held = int(own[-1]), counts[-1]
        if last >= 0:
            yield decide(np.array([last]), held[None])

    met = encoded.mapInArrow(scatter, "id int, slots binary").repartition("id").sortWithinPartitions("id")
    found = met.mapInArrow(gather, "id int, class smallint").toArrow()
    return found.column("id").to_numpy(), found.column("class").to_numpy()


#: Parts of the number that says what stands around a word: class before and after (plus 1; 0: not known), whether each is of the head, training text.
_PREV, _NEXT, _PREV_HEAD, _NEXT_HEAD, _TRAIN = 0, 12, 24, 25, 26
_CLASS = (1 << 12) - 1


def strange_words(encoded: DataFrame, of: np.ndarray, head: int) -> DataFrame:
    """(word, key, pos, around): every occurrence of a word that isn't known. of: a class for each id."""
    known = len(of) - 2
    of = np.r_[of, -1]  # id -1
    of[known + 1] = -1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, ids, starts in _slices(batches):
            at = np.flatnonzero(ids < 0)
            now, in_head = of[ids], (ids >= 0) & (ids < head) | (ids == known)
            doc = np.searchsorted(starts, at, side="right") - 1
            train = ~np.array(part.column("held_out").to_pylist(), bool)[doc]
            was, nxt = _before(now, of[known]), np.r_[now[1:], of[known]]
            around = (was[at] + 1 << _PREV) + (nxt[at] + 1 << _NEXT) + (_before(in_head, True)[at].astype(np.int64) << _PREV_HEAD) + (np.r_[in_head[1:], True][at].astype(np.int64) << _NEXT_HEAD) + (train.astype(np.int64) << _TRAIN)
            words = [w for x in part.column("strange").to_pylist() if x for w in x.split(b" ")]
            yield pa.RecordBatch.from_arrays([pa.array(words, pa.binary()), pa.array(part.column("key").to_numpy()[doc]), pa.array((at - starts[doc]).astype(np.int32)), pa.array(around.astype(np.int32))], names=["word", "key", "pos", "around"])

    return encoded.mapInArrow(run, "word binary, key bigint, pos int, around int")


def resolve(strange: DataFrame, table: np.ndarray, classes: int, least: int = LEAST) -> DataFrame:
    """(key, was, class, next, c, train) for every occurrence in strange_words(): the classes around it, its own, its word's count.

    next is -1 where another such word follows, which has this one before it.
    All occurrences of one word meet; as KNOWN words are more frequent, they
    are at most one in KNOWN of all tokens.
    """
    kinds = len(table)
    rare, choose = kinds - 2, class_chooser(table, classes)

    def assign(rows: pa.Table) -> pa.RecordBatch:
        word, around = rows.column("word").combine_chunks(), rows.column("around").to_numpy()
        fresh = np.r_[True, pc.not_equal(word[1:], word[:-1]).to_numpy(zero_copy_only=False)] if len(word) else np.zeros(0, bool)
        place = np.cumsum(fresh) - 1
        seen = np.flatnonzero(around >> _TRAIN & 1)
        c = np.bincount(place[seen], minlength=int(fresh.sum()))
        own = np.full(len(c), rare)
        todo = np.flatnonzero(c >= least)
        for a in range(0, len(todo), 512):
            some = todo[a : a + 512]
            lo, hi = np.searchsorted(place[seen], [some[0], some[-1] + 1])
            at = seen[lo:hi]
            row = np.searchsorted(some, place[at])
            row_ok = some[np.minimum(row, len(some) - 1)] == place[at]
            at, row = at[row_ok], row[row_ok]
            was, nxt = ((around[at] >> i & _CLASS) - 1 for i in (_PREV, _NEXT))
            was = np.where(around[at] >> _PREV_HEAD & 1, was, rare)
            nxt = np.where(around[at] >> _NEXT_HEAD & 1, nxt, rare)
            counts = np.bincount(np.r_[row * 2 * kinds + nxt, row * 2 * kinds + kinds + was], minlength=len(some) * 2 * kinds).reshape(len(some), -1)
            own[some] = choose(counts, c[some])
        return pa.RecordBatch.from_arrays([rows.column("key").combine_chunks(), rows.column("pos").combine_chunks(), pa.array(around), pa.array(own[place].astype(np.int16)), pa.array(c[place])], names=["key", "pos", "around", "class", "c"])

    def by_word(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for b in batches:
            if not b.num_rows:
                continue
            rows = pa.Table.from_batches([b]) if held is None else pa.concat_tables([held, pa.Table.from_batches([b])])
            word = rows.column("word").combine_chunks()
            same = pc.equal(word, word[-1]).to_numpy(zero_copy_only=False)
            whole = int(np.argmax(same))
            if whole:
                yield assign(rows.slice(0, whole))
            held = rows.slice(whole)
        if held is not None:
            yield assign(held)

    def by_text(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last = rare
        for b in batches:
            own, around = b.column("class").to_numpy(), b.column("around").to_numpy()
            if not len(own):
                continue
            was, nxt = ((around >> i & _CLASS) - 1 for i in (_PREV, _NEXT))
            was = np.where(was < 0, np.r_[last, own[:-1]], was)
            last = own[-1]
            yield pa.RecordBatch.from_arrays([b.column("key"), pa.array(was.astype(np.int16)), b.column("class"), pa.array(nxt.astype(np.int16)), b.column("c"), pa.array((around >> _TRAIN & 1).astype(bool))], names=["key", "was", "class", "next", "c", "train"])

    met = strange.repartition("word").sortWithinPartitions("word").mapInArrow(by_word, "key bigint, pos int, around int, class smallint, c bigint")
    return written(met.repartition("key").sortWithinPartitions("key", "pos").mapInArrow(by_text, "key bigint, was smallint, class smallint, next smallint, c bigint, train boolean"))


class WordClasses:
    """Classes of the known words; rare: the open class, end: that of the end of a text."""

    def __init__(self, known: np.ndarray, rare: int, end: int):
        self.known, self.rare, self.end = known, rare, end


class BrownModel:
    """Trained tables; score() gives base and model log10 probabilities of the texts, training texts and others."""

    def __init__(self, counts: DataFrame, texts: DataFrame, clustered: int | None = None, classes: int | None = None, known: int = KNOWN, sweeps: int = SWEEPS, prior: float = PRIOR):
        """counts: word_counts() of the training texts. texts: text as bytes, and doc_id and held_out unless all are training texts."""
        total = counts.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n"), F.count("*").alias("v")).first()
        self.tokens, self.vocabulary = int(total["n"]), int(total["v"])
        words = counts.where(F.col("word") != F.lit(END))
        top = words.where(F.col("c") >= least_count(words, known)).toArrow()
        first = sorted(zip((-c for c in top.column("c").to_pylist()), map(bytes, top.column("word").to_pylist()), strict=True))
        self.words = [w for _, w in first]
        seen = np.array([-c for c, _ in first], np.float64)
        ends = counts.where(F.col("word") == F.lit(END)).first()
        self.ends = ends = int(ends["c"]) if ends else 0
        often = words.where(F.col("c") >= LEAST).count()
        if classes is None:
            classes = min(MOST_CLASSES, max(CLASSES, math.ceil(np.cbrt(often))))
        head = min(max(CLUSTERED, HEAD * classes) if clustered is None else clustered, len(self.words))
        classes = max(1, min(classes, head))
        if "held_out" not in texts.columns:
            texts = texts.select(F.lit(None).cast("bigint").alias("doc_id"), F.lit(False).alias("held_out"), "text")
        self.encoded = encode(texts, self.words)
        train = self.encoded.where("NOT held_out")
        # Ids: the known words, the end, and last (as -1) any other word.
        by_id = np.r_[np.arange(head), np.full(len(self.words) - head, head), head + 1, head]
        pairs = _summed(pair_cells(train, by_id, head + 2), head + 2)
        self.of = exchange(pairs, head, classes, sweeps) if head else np.array([1, 2])
        kinds = int(self.of.max()) + 1
        rare, end = kinds - 2, kinds - 1
        table = np.zeros((kinds, kinds))
        np.add.at(table, (self.of[:, None], self.of[None, :]), pairs)
        of = np.r_[self.of[:head], np.full(len(self.words) - head, rare), end, rare]
        ids, found = known_classes(train, of, head, table, classes)
        of[ids] = found
        self.classes = WordClasses(of[:-1], rare, end)
        self.strange = resolve(strange_words(self.encoded, of, head), table, classes)
        learnt = self.strange.where("train")
        cell = lambda a, b: (F.col(a).cast("bigint") * kinds + F.col(b)).alias("cell")
        one = F.lit(1).cast("bigint").alias("n")
        open_of = np.r_[of[:-1], -1]
        cells = pair_cells(train, open_of, kinds).unionByName(learnt.select(cell("was", "class"), one)).unionByName(learnt.where("next >= 0").select(cell("class", "next"), one))
        table = _summed(cells, kinds).astype(np.float64)
        share = (table.sum(axis=0) + 1) / (table.sum() + kinds)
        self.transition = np.log10((table + prior * share) / (table.sum(axis=1, keepdims=True) + prior))
        #: Training tokens by class, and the open class's tokens and words.
        self.mass = table.sum(axis=0)
        self.rare_mass = float(self.mass[rare])
        self.rare_kinds = self.vocabulary - (ends > 0) - often - int((seen[:head] < LEAST).sum())
        own = self.classes.known[:-1]
        emission = np.log10(np.where(own == rare, (seen + 1) / (self.rare_mass + self.rare_kinds + 1), seen / np.maximum(self.mass[own], 1)))
        #: By id: the known words, the end, any other word.
        self.emission = np.r_[emission, 0.0, 0.0]
        self.base = np.r_[np.log10((np.r_[seen, ends] + 1) / (self.tokens + self.vocabulary + 1)), 0.0]

    def _known_part(self):
        of, emission, base, transition = np.r_[self.classes.known, -1], self.emission, self.base, self.transition
        counted = np.r_[np.ones(len(self.words), np.int64), int(self.ends > 0), 0]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for part, ids, starts in _slices(batches):
                now = of[ids]
                was = _before(now, of[-2])
                cost = emission[ids] + np.where((now >= 0) & (was >= 0), transition[was, now], 0.0)
                total = lambda x: np.add.reduceat(x, starts)
                made = [np.diff(np.r_[starts, len(ids)]), total(counted[ids]), total(base[ids]), total(cost)]
                yield pa.RecordBatch.from_arrays([part.column("key"), part.column("doc_id"), part.column("held_out"), *map(pa.array, made)], names=["key", "doc_id", "held_out", "n_tokens", "n_known", "base_score", "score"])

        return run

    def _strange_part(self):
        transition, rare = self.transition, self.classes.rare
        mass, open_mass, all_mass = np.maximum(self.mass, 1), self.rare_mass + self.rare_kinds + 1, self.tokens + self.vocabulary + 1

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                was, own, nxt, c = (b.column(x).to_numpy() for x in ("was", "class", "next", "c"))
                emission = np.log10(np.where(own == rare, (c + 1) / open_mass, np.maximum(c, 1) / mass[own]))
                cost = emission + transition[was, own] + np.where(nxt >= 0, transition[own, nxt], 0.0)
                yield pa.RecordBatch.from_arrays([b.column("key"), pa.array((c > 0).astype(np.int64)), pa.array(np.log10((c + 1) / all_mass)), pa.array(cost)], names=["key", "known", "base", "cost"])

        return run

    def score(self) -> DataFrame:
        """One row for each of the texts: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score."""
        texts = self.encoded.mapInArrow(self._known_part(), "key bigint, doc_id bigint, held_out boolean, n_tokens bigint, n_known bigint, base_score double, score double")
        more = self.strange.mapInArrow(self._strange_part(), "key bigint, known bigint, base double, cost double")
        more = more.groupBy("key").agg(F.sum("known").alias("known"), F.sum("base").alias("base"), F.sum("cost").alias("cost"))
        plus = lambda a, b: F.col(a) + F.coalesce(F.col(b), F.lit(0))
        return texts.join(more, "key", "left").select(
            "doc_id", "held_out", "n_tokens", plus("n_known", "known").alias("n_known"), F.lit(self.tokens).cast("bigint").alias("train_tokens"),
            plus("base_score", "base").alias("base_score"), plus("score", "cost").alias("score"),
        )


def train_and_score(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", clustered: int | None = None, classes: int | None = None, known: int = KNOWN) -> DataFrame:
    """Train on the rows that held_out() leaves, score all rows.

    Null text is empty: one token, the end. A null id counts as training.
    Repeated rows count as often as they occur and give repeated rows. Without
    training rows all counts are 0. Also gives perplexity per token. The head
    and the number of classes grow with the vocabulary unless they are given.
    """
    own = narrow(docs, id_col, text_col)
    texts = as_bytes(own.withColumn("held_out", held_out(F.col("doc_id"))), "held_out")
    counts = settle(word_counts(texts.where("NOT held_out").select("text")))
    model = BrownModel(counts, texts, clustered, classes, known)
    return model.score().withColumn("perplexity", F.pow(F.lit(10.0), -F.col("score") / F.col("n_tokens")))


def brute_scores(texts: list[tuple[bytes, bool]]) -> list[tuple[int, int, float]]:
    """(n_tokens, n_known, base score) by the definition, for tests."""
    counts: Counter = Counter()
    for text, out in texts:
        if not out:
            counts.update([*text.translate(LOWER).split(), END])
    n, v = sum(counts.values()), len(counts)
    split = [[*text.translate(LOWER).split(), END] for text, _ in texts]
    return [(len(t), sum(counts[w] > 0 for w in t), sum(math.log10((counts[w] + 1) / (n + v + 1)) for w in t)) for t in split]
