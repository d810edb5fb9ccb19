"""Substring deduplication by relative Lempel-Ziv parsing.

Documents are parsed into factors copied from elsewhere in the corpus.  Only factors of at least
``WINDOW`` words can become duplicate spans, so only those are sought: the reference is indexed by
anchors, the winnowing minima of ``SEED``-word hashes, of which every ``WINDOW``-word passage holds at
least one, and the same one wherever the passage occurs.  An anchor that occurs once can start no factor;
the others deal the passages around them to reference blocks.  A block's passages are sorted as suffixes,
so that the longest match of every place stands next to it; the parse goes greedily from the left, takes
the longest match as a factor and goes on at the first passage that reaches over the factor's end, so
boundaries are checked passage by passage.  Factors also end where the text around an anchor does; the
passages that reach over that border have anchors of their own, and :func:`stitched` joins factors that go
on in their source there.  So the spans are exactly the words of passages that start twice.  What a
document copies from itself it settles alone, and the blocks get each passage of a document once.

Documents of equal words are parsed once; such a class repeats itself and is one factor.  An anchor with
more than ``HOT_ROWS`` occurrences isn't gathered in a block: they are dealt by document to blocks of
about that many first, which settle what repeats inside and pass on one occurrence of each passage, and
those meet by passage in blocks of bounded size.  So a passage of any number of documents reaches a task
once per first block at most.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from incstate.llm.common import Ragged, bound_batches, cut, flat, mix64, slices, written

WINDOW = 35
SEED = 8
HOT_ROWS = 1000
BLOCK_POSITIONS = 400_000

_ROLL = 0xD1342543DE82EF95 | 1
_UNROLL = pow(_ROLL, -1, 1 << 64)
_PLACE = 26
#: Words whose anchors are sought at a time.
PIECE = 1 << 25


class Parsed:
    """Words of some texts with passage hashes and the anchor of every passage."""

    def __init__(self, texts: pa.Array, window: int = WINDOW, seed: int = SEED):
        self.words = words = Ragged(texts)
        h = words.hashes()
        n = len(h)
        self.seq = self._sequences(h)
        room = np.repeat(words.first[1:], words.counts) - np.arange(n)
        self.ok = room >= window
        powers = np.full(n + 1, _ROLL, np.uint64)
        powers[0] = 1
        np.multiply.accumulate(powers, out=powers)
        run = np.zeros(n + 1, np.uint64)
        np.cumsum(h * powers[:n], out=run[1:])
        back = np.full(n + 1, _UNROLL, np.uint64)
        back[0] = 1
        np.multiply.accumulate(back, out=back)

        def passage(k: int) -> np.ndarray:
            out = np.zeros(n, np.uint64)
            if n >= k:
                out[: n - k + 1] = mix64((run[k:] - run[:-k]) * back[: n - k + 1])
            return out

        self.window_hash = passage(window)
        self.seed_hash = passage(seed)
        self.anchor = self._minima(self.seed_hash, window - seed + 1)

    def _sequences(self, h: np.ndarray) -> np.ndarray:
        """A hash of each document's whole word sequence."""
        place = (np.arange(len(h)) - np.repeat(self.words.first[:-1], self.words.counts)).astype(np.uint64)
        salted = mix64(h ^ mix64(place + np.uint64(0x632BE59BD9B4E019)))
        run = np.concatenate((np.zeros(1, np.uint64), np.cumsum(salted, dtype=np.uint64)))
        return mix64(run[self.words.first[1:]] - run[self.words.first[:-1]] + self.words.counts.astype(np.uint64)).view(np.int64)

    @staticmethod
    def _minima(values: np.ndarray, span: int, piece: int | None = None) -> np.ndarray:
        """For each position the place of the least of the next ``span`` values, the first of equals."""
        piece = piece or PIECE
        if len(values) > piece:
            parts = range(0, len(values), piece)
            return np.concatenate([x + Parsed._minima(values[x : x + piece + span - 1], span, 2 * piece)[:piece] for x in parts])
        n = len(values)
        if not n:
            return np.zeros(0, np.int64)
        most = np.uint64((1 << _PLACE) - 1)
        key = np.full(-(-(n + span) // span) * span, np.iinfo(np.uint64).max, np.uint64)
        key[:n] = (values & ~most) | np.arange(n, dtype=np.uint64)
        grid = key.reshape(-1, span)
        ahead = np.minimum.accumulate(grid, axis=1).ravel()
        behind = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
        return (np.minimum(behind[:n], ahead[span - 1 : span - 1 + n]) & most).astype(np.int64)


@F.arrow_udf(
    T.StructType().add("seq", "long").add("n", "long").add("at", T.ArrayType(T.ArrayType(T.IntegerType()))).add("anchor", T.ArrayType(T.LongType()))
)
def _profile(text: pa.Array) -> pa.Array:
    """Word sequence, number of words, and the distinct anchors with the places of each."""
    seq, n, doc_ends, place_ends, at, anchor = [], [], [np.zeros(1, np.int64)], [np.zeros(1, np.int64)], [], []
    text = flat(text)
    for a, b in slices(text):
        p = Parsed(text[a:b])
        place = np.unique(p.anchor[p.ok])
        doc, value = p.words.doc[place], p.seed_hash[place]
        order = np.lexsort((place, value, doc))
        place, doc, value = place[order], doc[order], value[order]
        new = np.flatnonzero(np.concatenate(([True], (np.diff(value) != 0) | (np.diff(doc) != 0)))) if len(place) else place
        seq.append(p.seq)
        n.append(p.words.counts)
        at.append(place - p.words.first[doc])
        anchor.append(value[new])
        place_ends.append(place_ends[-1][-1] + np.append(new[1:], len(place))[: len(new)])
        doc_ends.append(doc_ends[-1][-1] + np.cumsum(np.bincount(doc[new], minlength=b - a)))
        if not len(new):
            place_ends.pop()
    joined = lambda x, kind: np.concatenate(x) if x else np.zeros(0, kind)
    ends = pa.array(np.concatenate(doc_ends), pa.int32())
    places = pa.ListArray.from_arrays(pa.array(np.concatenate(place_ends), pa.int32()), pa.array(joined(at, np.int64), pa.int32()))
    return pa.StructArray.from_arrays(
        [
            pa.array(joined(seq, np.int64)),
            pa.array(joined(n, np.int64)),
            pa.ListArray.from_arrays(ends, places),
            pa.ListArray.from_arrays(ends, pa.array(joined(anchor, np.uint64).view(np.int64))),
        ],
        names=["seq", "n", "at", "anchor"],
    )


_FACTOR = "seq long, start int, length int, source_seq long, source_start int"
_PASSAGE = "anchor long, rows long, seq long, start int, passages array<long>, length int, source_start int"


def _own_repeats(doc: np.ndarray, value: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For passages in order of place: whether their document repeats them, the place (as an index) that they
    copy, which is the one before or, for the first, the next, and whether they are the first."""
    n = len(value)
    key = value ^ mix64(doc.astype(np.uint64) + np.uint64(1))
    order = np.argsort(key, kind="stable")
    same = np.concatenate((key[order[1:]] == key[order[:-1]], [False])) if n else np.zeros(0, bool)
    first, source = np.ones(n, bool), np.full(n, -1, np.int64)
    first[order[1:][same[:-1]]] = False
    source[order[:-1][same[:-1]]] = order[1:][same[:-1]]
    source[order[1:][same[:-1]]] = order[:-1][same[:-1]]
    return source >= 0, source, first


def _runs(*steps: np.ndarray) -> np.ndarray:
    """Where runs begin in arrays that grow by one within a run (``steps`` beyond the first may also stay)."""
    if not len(steps[0]):
        return np.zeros(0, np.int64)
    new = np.diff(steps[0]) != 1
    for s in steps[1:]:
        new |= np.diff(s) != 0
    return np.flatnonzero(np.concatenate(([True], new)))


def _passages(batches):
    """Texts with their repeated anchors to rows of two kinds.

    Factors that a text copies from itself have a ``length`` and a ``source_start``; for the blocks, each
    place of an anchor has its run of ``passages``, those that the text has had before left out.
    """
    for batch in batches:
        text, seq = batch.column("text"), batch.column("seq").to_numpy()
        spots = batch.column("spots")
        for a, b in slices(text):
            p = Parsed(text[a:b])
            part = spots[a:b]
            doc = np.repeat(np.arange(b - a), np.diff(part.offsets.to_numpy()))
            held = part.flatten()
            lists = held.field("at")
            sizes = np.diff(lists.offsets.to_numpy())
            doc, many = np.repeat(doc, sizes), np.repeat(held.field("rows").to_numpy(), sizes)
            good = (p.seq == seq[a:b])[doc]
            wanted = np.zeros(len(p.ok) + 1, np.int64)
            wanted[(lists.flatten().to_numpy() + p.words.first[doc])[good]] = many[good]
            row = np.flatnonzero(p.ok & (wanted[p.anchor] > 0) if len(p.ok) else p.ok)
            of = p.words.doc[row]
            twice, source, first = _own_repeats(of, p.window_hash[row])
            own, copied = row[twice], row[source[twice]]
            new = _runs(own, of[twice], copied - own)
            at = p.words.first[of[twice][new]]
            length = np.diff(np.append(new, len(own))) + WINDOW - 1
            none = pa.nulls(len(new), pa.int64())
            yield pa.RecordBatch.from_arrays(
                [none, none, pa.array(p.seq[of[twice][new]]), pa.array(own[new] - at, pa.int32()), pa.nulls(len(new), pa.list_(pa.int64())), pa.array(length, pa.int32()), pa.array(copied[new] - at, pa.int32())],
                names=["anchor", "rows", "seq", "start", "passages", "length", "source_start"],
            )
            row, of = row[first], of[first]
            spot = p.anchor[row]
            new = _runs(row, spot)
            of = of[new]
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(p.seed_hash[spot[new]].view(np.int64)),
                    pa.array(wanted[spot[new]]),
                    pa.array(p.seq[of]),
                    pa.array(row[new] - p.words.first[of], pa.int32()),
                    pa.ListArray.from_arrays(pa.array(np.append(new, len(row)), pa.int32()), pa.array(p.window_hash[row].view(np.int64))),
                    pa.nulls(len(new), pa.int32()),
                    pa.nulls(len(new), pa.int32()),
                ],
                names=["anchor", "rows", "seq", "start", "passages", "length", "source_start"],
            )




def _occurrences(table: pa.Table) -> tuple[np.ndarray, ...]:
    """All passages of a block's rows: row number, passage, sequence and place of each."""
    lists = flat(table.column("passages"))
    seq, start = (table.column(c).to_numpy() for c in ("seq", "start"))
    sizes = np.diff(lists.offsets.to_numpy())
    # Repeated rows of a document come as equal rows.
    order = np.lexsort((start, seq))
    again = np.zeros(len(seq), bool)
    again[order[1:]] = (np.diff(seq[order]) == 0) & (np.diff(start[order]) == 0)
    row = np.repeat(np.arange(len(seq)), sizes)
    offset = np.arange(len(row)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    use = ~again[row]
    row, offset = row[use], offset[use]
    return row, lists.flatten().to_numpy()[use], seq[row], start[row] + offset


def _sources(value: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Whether each occurrence of a passage has another one, and whether it's the passage's first."""
    order = np.argsort(value, kind="stable")
    v = value[order]
    new = np.concatenate(([True], np.diff(v) != 0)) if len(v) else np.zeros(0, bool)
    count = np.diff(np.append(np.flatnonzero(new), len(v)))
    dup, lead = np.zeros(len(v), bool), np.zeros(len(v), bool)
    dup[order], lead[order] = np.repeat(count, count) > 1, new
    return dup, lead


def longest_matches(value: np.ndarray, left: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of each place the length of its longest match elsewhere, in passages, and the place that it matches.

    ``left`` counts the places from each one to the end of its text, itself included.  Texts are sorted as
    suffixes by doubling; a longest match is the common prefix with a neighbour in that order.
    """
    n = len(value)
    place, rank = np.arange(n), np.unique(value, return_inverse=True)[1].astype(np.int64)
    ranks, p = [rank], 1
    while p < left.max(initial=0):
        more = left > p
        after = np.zeros(n, np.int64)
        after[more] = rank[place[more] + p] + 1
        rank = np.unique(rank * (n + 1) + after, return_inverse=True)[1].astype(np.int64)
        ranks.append(rank)
        p *= 2
    order = np.argsort(rank, kind="stable")
    a, b = order[:-1], order[1:]
    room, common = np.minimum(left[a], left[b]), np.zeros(max(n - 1, 0), np.int64)
    for j in range(len(ranks) - 1, -1, -1):
        fits = np.flatnonzero(common + (1 << j) <= room)
        same = fits[ranks[j][a[fits] + common[fits]] == ranks[j][b[fits] + common[fits]]]
        common[same] += 1 << j
    before, behind = np.concatenate(([0], common)), np.concatenate((common, [0]))
    length, source = np.zeros(n, np.int64), np.zeros(n, np.int64)
    length[order] = np.maximum(before, behind)[:n]
    source[order] = np.where(before >= behind, np.concatenate((order[:1], a)), np.concatenate((b, order[-1:])))[:n]
    return length, source


def _parse(table: pa.Table) -> pa.Table:
    """Factors of the passages of one reference block."""
    row, value, who, where = _occurrences(table)
    return _factors(row, value, who, where, _sources(value)[0])


def _factors(row: np.ndarray, value: np.ndarray, who: np.ndarray, where: np.ndarray, dup: np.ndarray) -> pa.Table:
    """The greedy parse of repeated passages: the longest match from the left, then the next passage over its end."""
    keep = np.flatnonzero(dup)
    head = np.flatnonzero(np.concatenate(([True], (np.diff(keep) != 1) | (np.diff(row[keep]) != 0)))) if len(keep) else keep
    size = np.diff(np.append(head, len(keep)))
    end = np.repeat(head + size, size)
    length, source = longest_matches(value[keep], end - np.arange(len(keep)))
    at, found = head, []
    while len(at):
        found.append(at)
        ahead = at + length[at]
        at = ahead[ahead < end[at]]
    at = np.sort(np.concatenate(found)) if found else keep
    copy = keep[source[at]]
    return pa.table(
        {
            "seq": pa.array(who[keep[at]], pa.int64()),
            "start": pa.array(where[keep[at]], pa.int32()),
            "length": pa.array(length[at] + WINDOW - 1, pa.int32()),
            "source_seq": pa.array(who[copy], pa.int64()),
            "source_start": pa.array(where[copy], pa.int32()),
        }
    )


_CROWD = _FACTOR + ", anchor long, sub int, values array<long>, seqs array<long>, starts array<int>, sure array<boolean>"


def _crowd_parse(table: pa.Table) -> pa.Table:
    """A first block of a crowded anchor: its factors, and one occurrence of each passage, dealt by passage."""
    row, value, who, where = _occurrences(table)
    dup, lead = _sources(value)
    made = _factors(row, value, who, where, dup)
    subs = int(table.column("subs")[0].as_py())
    sub = (value[lead].view(np.uint64) % np.uint64(subs)).astype(np.int64)
    order = np.argsort(sub, kind="stable")
    names, first = np.unique(sub[order], return_index=True)
    ends = pa.array(np.append(first, len(order)), pa.int32())
    columns = {"values": value[lead][order], "seqs": who[lead][order], "starts": where[lead][order].astype(np.int32), "sure": dup[lead][order]}
    n, k = made.num_rows, len(names)
    out = {c: pa.concat_arrays([flat(made.column(c)), pa.nulls(k, made.schema.field(c).type)]) for c in made.column_names}
    out["anchor"] = pa.array([None] * n + [table.column("anchor")[0].as_py()] * k, pa.int64())
    out["sub"] = pa.array([None] * n + names.tolist(), pa.int32())
    for name, x in columns.items():
        lists = pa.ListArray.from_arrays(ends, pa.array(x))
        out[name] = pa.concat_arrays([pa.nulls(n, lists.type), lists])
    return pa.table(out)


def _meet(table: pa.Table) -> pa.Table:
    """Passages that repeat only across first blocks."""
    value, who, where, sure = (flat(table.column(c)).flatten().to_numpy(zero_copy_only=False) for c in ("values", "seqs", "starts", "sure"))
    length, source = longest_matches(value, np.ones(len(value), np.int64))
    at = np.flatnonzero((length > 0) & ~sure.astype(bool))
    return pa.table(
        {
            "seq": pa.array(who[at], pa.int64()),
            "start": pa.array(where[at], pa.int32()),
            "length": pa.array(np.full(len(at), WINDOW), pa.int32()),
            "source_seq": pa.array(who[source[at]], pa.int64()),
            "source_start": pa.array(where[source[at]], pa.int32()),
        }
    )


def _rows(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """``(profile, classes)``: one row per (id, text) with its anchors, and the classes of equal word sequences.

    A row is known by its id and a hash of its text, so null and repeated ids stay apart.  A class has one
    such row as ``rep`` (one that isn't repeated, where there is any) and the number of its ``copies``.
    """
    text = F.coalesce("text", F.lit(""))
    profile = written(docs.select("doc_id", F.xxhash64(text).alias("mark"), _profile(text).alias("p")).select("doc_id", "mark", "p.*"))
    rows = profile.groupBy("seq", "doc_id", "mark").agg(F.count("*").alias("times"), F.max("n").alias("n"))
    classes = cut(
        rows.groupBy("seq").agg(F.sum("times").alias("copies"), F.min(F.struct("times", "doc_id", "mark")).alias("rep"), F.max("n").alias("n"))
    )
    return profile, classes


def _by_row(rows: DataFrame, per: DataFrame) -> DataFrame:
    """``rows`` with (doc_id, mark) joined to ``per`` with (_id, _mark)."""
    return rows.join(per, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("mark") == F.col("_mark"))).drop("_id", "_mark")


def _found(docs: DataFrame, hot_rows: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """``(profile, classes, found)``: see :func:`_rows`; ``found`` are the factors of classes."""
    bound_batches(docs)
    base = docs.select("doc_id", "text")
    profile, classes = _rows(base)
    long_ones = classes.where(F.col("n") >= WINDOW)
    reps = long_ones.select("seq", F.col("rep.doc_id").alias("_id"), F.col("rep.mark").alias("_mark"))
    again = not long_ones.where("rep.times > 1").isEmpty()

    def once(rows: DataFrame) -> DataFrame:
        """One row of each class, where rows of one id and text are its only ones."""
        return rows.dropDuplicates(["seq"]) if again else rows

    spots = once(_by_row(profile.drop("seq"), reps)).select("seq", F.explode(F.arrays_zip("at", "anchor")).alias("x")).select("seq", "x.at", "x.anchor")
    # Cut off, so that a join with a frequent anchor can be split.
    known = cut(spots.groupBy("anchor").agg(F.count("*").alias("rows"), F.sum(F.size("at")).alias("places")).where("places > 1").drop("places"))
    shared = spots.join(known, "anchor").groupBy("seq").agg(F.collect_list(F.struct("at", "rows")).alias("spots"))
    text = F.coalesce("text", F.lit(""))
    passages = written(
        once(_by_row(base.select("doc_id", F.xxhash64(text).alias("mark"), text.alias("text")), shared.join(reps, "seq")))
        .select("seq", "text", "spots")
        .mapInArrow(_passages, _PASSAGE)
    )
    own = passages.where("length is not null").select("seq", "start", "length", F.col("seq").alias("source_seq"), "source_start")
    passages = passages.where("length is null").drop("length", "source_start")
    total = passages.agg(F.sum(F.size("passages"))).first()[0] or 0
    blocks = max(int(base.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-total // BLOCK_POSITIONS))
    parsed = (
        passages.where(F.col("rows") <= hot_rows)
        .groupBy(F.pmod(F.xxhash64("anchor"), F.lit(blocks)).alias("block"))
        .applyInArrow(_parse, _FACTOR)
    )
    crowd = (
        passages.where(F.col("rows") > hot_rows)
        .withColumn("subs", F.ceil(F.col("rows") / hot_rows))
        .withColumn("salt", F.pmod(F.xxhash64("seq"), F.col("subs")))
    )
    first = written(crowd.groupBy("anchor", "salt").applyInArrow(_crowd_parse, _CROWD))
    names = [c.split(" ")[0] for c in _FACTOR.split(", ")]
    across = first.where("sub is not null").groupBy("anchor", "sub").applyInArrow(_meet, _FACTOR)
    found = own.unionByName(parsed).unionByName(first.where("sub is null").select(*names)).unionByName(across)
    return profile, classes, found


def stitched(found: DataFrame) -> DataFrame:
    """Factors that go on in their source without a gap, as one factor each."""
    shift = F.col("source_start") - F.col("start")
    line = Window.partitionBy("seq", "source_seq", "shift").orderBy("start", "length")
    end = F.max(F.col("start") + F.col("length")).over(line.rowsBetween(Window.unboundedPreceding, -1))
    # A factor's last passage starts WINDOW words before its end, and the next one at most one word on.
    begins = (end.isNull() | (F.col("start") > end - WINDOW + 1)).cast("int")
    return (
        found.withColumn("shift", shift).withColumn("begins", begins).withColumn("nth", F.sum("begins").over(line.rowsBetween(Window.unboundedPreceding, 0)))
        .groupBy("seq", "source_seq", "shift", "nth")
        .agg(F.min("start").alias("start"), (F.max(F.col("start") + F.col("length")) - F.min("start")).alias("length"))
        .select("seq", "start", "length", "source_seq", (F.col("start") + F.col("shift")).alias("source_start"))
    )


def factors(docs: DataFrame, hot_rows: int = HOT_ROWS) -> tuple[DataFrame, DataFrame]:
    """The parse of ``docs(doc_id, text)``.

    Returns ``(rows, found)``: ``rows(doc_id, n, seq, copies)`` has one row for each distinct (doc_id, word
    sequence), ``copies`` counting the input rows of that sequence; ``found(seq, start, length, source_seq,
    source_start)`` the factors of ``WINDOW`` words or more of sequences, in words from 0.
    """
    profile, classes, found = _found(docs, hot_rows)
    return profile.select("doc_id", "n", "seq").distinct().join(classes.select("seq", "copies"), "seq"), stitched(found)


@F.arrow_udf(T.StructType().add("n_words", "long").add("n_removed", "long").add("kept", "string"))
def _cut_out(text: pa.Array, seq: pa.Array, whole: pa.Array, spans: pa.Array) -> pa.Array:
    text, seq, whole, spans = (flat(x) for x in (text, seq, whole, spans))
    n_words, n_removed, kept = [], [], []
    for a, b in slices(text):
        p = Parsed(text[a:b])
        w = p.words
        gone = np.zeros(len(w.starts) + 1, np.int64)
        part = spans[a:b]
        doc = np.repeat(np.arange(b - a), np.diff(part.offsets.to_numpy()))
        held = part.flatten()
        begin = w.first[doc] + held.field("start").to_numpy()
        match = p.seq == seq[a:b].to_numpy()
        ok = match[doc]
        np.add.at(gone, begin[ok], 1)
        np.add.at(gone, (begin + held.field("length").to_numpy())[ok], -1)
        lost = np.cumsum(gone[:-1]) > 0
        lost |= (whole[a:b].to_numpy(zero_copy_only=False) & (w.counts >= WINDOW))[w.doc]
        n_words += w.counts.tolist()
        n_removed += np.bincount(w.doc[lost], minlength=b - a).tolist()
        raw = w.bytes.tobytes()
        left = ~lost
        for i in range(b - a):
            s = np.s_[w.first[i] : w.first[i + 1]]
            kept.append(b" ".join([raw[x:y] for x, y in zip(w.starts[s][left[s]].tolist(), w.ends[s][left[s]].tolist())]).decode())
    return pa.StructArray.from_arrays(
        [pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(kept, pa.string())],
        names=["n_words", "n_removed", "kept"],
    )


def without_repeats(docs: DataFrame, hot_rows: int = HOT_ROWS) -> DataFrame:
    """``row, n_words, n_removed, kept``: the input rows as structs, with the words left joined by one blank.

    A word goes if some ``WINDOW``-word passage over it also starts at another place of any document, the
    same one included; passages are judged on the input.  Null texts count as empty; texts of fewer than
    ``WINDOW`` words lose nothing; repeated rows repeat each other, so long ones lose every word.  Null and
    repeated ids are rows of their own.  A text of any length is worked on as a whole, about 150 bytes of
    memory a word.  An empty table gives no rows.
    """
    profile, classes, found = _found(docs, hot_rows)
    spans = found.groupBy("seq").agg(F.collect_list(F.struct("start", "length")).alias("spans"))
    none = F.array().cast("array<struct<start:int,length:int>>")
    # Repeated classes lose all their words and need no spans; the others are one row each.
    single = classes.where("copies = 1").join(spans, "seq").select("seq", F.col("rep.doc_id").alias("_id"), F.col("rep.mark").alias("_mark"), "spans")
    many = classes.where(f"copies > 1 and n >= {WINDOW}").select("seq")
    lost = profile.join(many, "seq").select("seq", F.col("doc_id").alias("_id"), F.col("mark").alias("_mark")).distinct()
    per = single.withColumn("whole", F.lit(False)).unionByName(lost.withColumn("whole", F.lit(True)).withColumn("spans", none))
    whole_rows = docs.select(
        F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col("doc_id"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("mark")
    )
    met = whole_rows.join(per, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("mark") == F.col("_mark")), "left")
    out = _cut_out(F.coalesce("row.text", F.lit("")), F.coalesce("seq", F.lit(0)), F.coalesce("whole", F.lit(False)), F.coalesce("spans", none))
    return met.select("row", out.alias("out")).select("row", "out.n_words", "out.n_removed", "out.kept")


def digest(docs: DataFrame, hot_rows: int = HOT_ROWS) -> DataFrame:
    """``doc_id, n_words, n_removed, kept_sha256`` of :func:`without_repeats`; other columns are ignored."""
    return without_repeats(docs.select("doc_id", "text"), hot_rows).select(
        "row.doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256")
    )


def drop_repeats(docs: DataFrame) -> DataFrame:
    """``docs`` with repeated passages cut from ``text`` where there are any; documents left without words go."""
    done = without_repeats(docs).where("n_removed < n_words or n_words = 0")
    text = F.when(F.col("n_removed") > 0, F.col("kept")).otherwise(F.col("row.text")).alias("text")
    return done.select(*[text if c == "text" else F.col(f"row.`{c}`") for c in docs.columns])
