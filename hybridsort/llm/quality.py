"""Quality rules and n-gram perplexity bands.

Texts become sequences of 64 character classes: letters without case, white space, digits, groups of
marks, and bytes of other characters folded by their lead. Spark counts the four-grams of every text
for each language; there are at most 2**24 of them, so a language's model has a proven bound. From
the counts a modified Kneser-Ney model is made: raw counts at the highest order, counts of different
predecessors below, three discounts at each order. It is kept as sorted arrays of packed n-grams with
their probabilities, and of contexts with their back-off weights.

Each text then gets its bits per character under its language's model. The band of a language is
its quartiles widened by a multiple of their distance; texts outside it, to either side, are
rejected, as are those that fail the base rules. Quartiles are over distinct texts, so that copies of
a text, however many, move no band, and their distance counts as LEAST_SPREAD bits at least, so that
a language of few or very like texts keeps a band.

Above that stands a model of pairs of word pieces, whose number grows with the input: a word and the blank
before it are cut into pieces of four bytes, and a piece is foretold by the one before it, across words
too. Its modified Kneser-Ney estimate leans on the character model for a piece's own probability. No task
holds this model. Rows are gathered into parts of a few megabytes, the same ones whenever the input is read; a part
counts its pairs and sends them, as sorted arrays of differences, to shards by the hash of the first
piece. A shard adds the counts up and answers each part, in the order of its pairs, with totals and with
what follows each first piece; parts meet their answers compressed. A text's own pairs are taken off all these numbers exactly, as it
would foretell itself. Only the upper edge of the band rejects here: text that others repeat is left to
deduplication.

Defined results: null text has no words and fails the base rules; a null language is a language of
its own; an empty table gives no rows; repeated rows are judged each and counted each in the model,
but once in the band; a text without any character scores 0 bits.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACE, column, give_back, gram_hashes, light_batches, mix, packed, repeatable, split_words, staged, text_slices, tidy, unpacked, without, word_hashes

ORDER, BITS = 4, 6
GAP = b"\n" * (ORDER - 1)
SYMBOLS = np.frombuffer(b"#*$%&|<>", np.uint8)
#: Bits a character that the quartiles of a language count as apart at least.
LEAST_SPREAD = 0.02
#: Bytes of text of a part, and shuffle partitions for each shard of a language's pairs.
PART_BYTES, TO_A_SHARD = 3 << 20, 4
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "bits_per_char", "piece_bits_per_char")
ADDED = (*MEASURES, "lang_group", "text_digest", "base_failed", "kept")


def _classes() -> np.ndarray:
    out = np.full(256, 31, np.uint32)
    for marks, k in ((b" \t\n\v\f\r", 0), (b"0123456789", 27), (b".,;:!?", 28), (b"\"'()[]{}", 29), (b"#*$%&|<>=+-_/\\@^~`", 30)):
        out[list(marks)] = k
    for b in range(26):
        out[[65 + b, 97 + b]] = 1 + b
    for b in range(128, 192):
        out[b] = 48 + b % 16
    for b in range(192, 256):
        out[b] = 32 + b % 16
    return out


CLASS = _classes()


def packed_grams(buffer: bytes) -> np.ndarray:
    """For each byte, its class and those of the three before it, as 24 bits."""
    c = CLASS[np.frombuffer(GAP + buffer, np.uint8)]
    return c[3:] | (c[2:-1] << np.uint32(BITS)) | (c[1:-2] << np.uint32(2 * BITS)) | (c[:-3] << np.uint32(3 * BITS))


@tidy
def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        langs = np.array([x or "" for x in column(batch, "lang").to_pylist()], object)
        found: dict[str, list[np.ndarray]] = {}
        for first, rows, buffer, starts in text_slices(column(batch, "text"), GAP):
            grams = packed_grams(buffer)
            own = langs[first : first + rows]
            for lang in set(own):
                mine = own == lang
                part = grams if mine.all() else grams[np.repeat(mine, np.diff(starts))]
                found.setdefault(lang, []).append(np.unique(part, return_counts=True))
        for lang, parts in found.items():
            grams = np.concatenate([g for g, _ in parts])
            order = np.argsort(grams, kind="stable")
            grams, n = grams[order], np.concatenate([n for _, n in parts])[order]
            first = np.flatnonzero(np.diff(grams, prepend=np.uint32(1 << 31)))
            if len(first):
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(first), pa.string()), pa.array(grams[first].astype(np.int32)), pa.array(np.add.reduceat(n, first).astype(np.int64))], names=["lang", "gram", "n"])


def gram_counts(docs: DataFrame) -> DataFrame:
    """lang, gram and n over all texts; each task sends a row a language and gram at most."""
    return docs.select("lang", "text").mapInArrow(_count, "lang string, gram int, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))


def discounts(n1: int, n2: int, n3: int, n4: int) -> tuple[float, float, float]:
    """What is taken off counts of one, two, and three or more, from how many n-grams have one to four."""
    n1, n2, n3, n4 = (max(1, n) for n in (n1, n2, n3, n4))
    y = n1 / (n1 + 2 * n2)
    return tuple(min(max(d, 0.05), cap - 0.05) for d, cap in ((1 - 2 * y * n2 / n1, 1), (2 - 3 * y * n3 / n2, 2), (3 - 4 * y * n4 / n3, 3)))


class KneserNey:
    """Modified Kneser-Ney over packed grams, as sorted arrays for each order.

    ``probability[k]`` are those of the seen (k + 1)-grams ``grams[k]``, interpolation included;
    ``backoff[k]`` are the weights of the seen contexts ``contexts[k]`` of k symbols.
    """

    def __init__(self, grams: np.ndarray, counts: np.ndarray):
        order = np.argsort(grams)
        top, n = grams[order].astype(np.int64), counts[order].astype(np.float64)
        levels = [(top, n)]
        for k in range(ORDER - 1, 0, -1):  # how many different symbols precede each shorter gram
            suffix, kinds = np.unique(levels[0][0] & ((1 << (BITS * k)) - 1), return_counts=True)
            levels.insert(0, (suffix, kinds.astype(np.float64)))
        self.grams, self.probability, self.contexts, self.backoff = [], [], [], []
        lower = None
        for k, (g, c) in enumerate(levels):
            d1, d2, d3 = self.discounts(c)
            context, first = np.unique(g >> BITS, return_index=True)
            total = np.add.reduceat(c, first)
            cut = np.where(c == 1, d1, np.where(c == 2, d2, d3))
            weight = np.add.reduceat(cut, first) / total
            at = np.repeat(np.arange(len(context)), np.diff(np.append(first, len(g))))
            below = np.full(len(g), 1 / (1 << BITS)) if lower is None else lower(g & ((1 << (BITS * k)) - 1))
            self.grams.append(g)
            self.probability.append((c - cut) / total[at] + weight[at] * below)
            self.contexts.append(context)
            self.backoff.append(weight)
            lower = lambda x, k=k: self._at(x, k)

    @staticmethod
    def discounts(c: np.ndarray) -> tuple[float, float, float]:
        return discounts(*(int((c == k).sum()) for k in (1, 2, 3, 4)))
    def _at(self, x: np.ndarray, k: int) -> np.ndarray:
        """Probability of (k + 1)-grams, seen or not."""
        g = self.grams[k]
        at = np.minimum(np.searchsorted(g, x), len(g) - 1)
        out = self.probability[k][at]
        rest = np.flatnonzero(g[at] != x)
        if len(rest):
            y = x[rest]
            c = self.contexts[k]
            at = np.minimum(np.searchsorted(c, y >> BITS), len(c) - 1)
            weight = np.where(c[at] == y >> BITS, self.backoff[k][at], 1.0)
            out[rest] = weight * (self._at(y & ((1 << (BITS * k)) - 1), k - 1) if k else 1 / (1 << BITS))
        return out

    def bits(self, grams: np.ndarray) -> np.ndarray:
        return -np.log2(self._at(grams.astype(np.int64), ORDER - 1))


class _Lookup:
    """Bits of packed grams, a row of symbols for each context once it has been met."""

    def __init__(self, model: KneserNey):
        self.model = model
        self.row = np.zeros(1 << (BITS * (ORDER - 1)), np.int32)
        self.bits = np.zeros((1, 1 << BITS), np.float32)

    def __call__(self, grams: np.ndarray) -> np.ndarray:
        context = grams >> np.uint32(BITS)
        row = self.row[context]
        fresh = np.unique(context[row == 0])
        if len(fresh):
            self.row[fresh] = len(self.bits) + np.arange(len(fresh))
            new = [self.bits]
            for a in range(0, len(fresh), 1024):  # the arrays of a search stay small
                every = (fresh[a : a + 1024].astype(np.int64)[:, None] << BITS) | np.arange(1 << BITS)
                new.append(self.model.bits(every.ravel()).reshape(-1, 1 << BITS).astype(np.float32))
            self.bits = np.concatenate(new)
            row = self.row[context]
        return self.bits[row, grams & np.uint32((1 << BITS) - 1)]


def repeated_trigram_words(hashes: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Words of each text inside three-word windows that the text has twice or more; hashes of all its words, and each text's first."""
    n = len(first) - 1
    counts = np.diff(first)
    if len(hashes) < 3:
        return np.zeros(n, np.int64)
    row = np.repeat(np.arange(n), counts)
    inside = row[:-2] == row[2:]
    key = gram_hashes(hashes, 3) ^ (row[:-2].astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))
    at = np.flatnonzero(inside)
    order = at[np.argsort(key[at], kind="stable")]
    same = key[order][1:] == key[order][:-1]
    twice = np.zeros(len(order), bool)
    twice[1:] |= same
    twice[:-1] |= same
    covered = np.zeros(len(hashes), bool)
    for k in range(3):
        covered[order[twice] + k] = True
    return np.bincount(row[covered], minlength=n)


def pieces(buffer: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Where each piece begins, and its four bytes as a number; a word's first piece holds a blank and three of its bytes."""
    n = len(buffer)
    data = np.frombuffer(b" " + buffer.lower() + bytes(4), np.uint8)
    space = SPACE[data[: n + 2]]
    space[-1] = True
    begins = np.flatnonzero(space[:-1] & ~space[1:]) + 1  # one past its place in the buffer
    ends = np.flatnonzero(~space[:-1] & space[1:]) + 1
    many = (ends - begins + 4) // 4
    nth = np.arange(int(many.sum())) - np.repeat(np.cumsum(many) - many, many)
    at, end = np.repeat(begins - 1, many) + 4 * nth, np.repeat(ends, many)
    code = np.where(nth == 0, 32, data[at]).astype(np.uint64) << np.uint64(24)
    for k in (1, 2, 3):
        code |= np.where(at + k < end, data[at + k], 0).astype(np.uint64) << np.uint64(24 - 8 * k)
    return np.maximum(at - 1 + (nth == 0), 0), code


class Pairs:
    """The pairs of pieces of some texts of one language, by shard and in order within it.

    ``code`` are the distinct pairs, ``place`` the distinct pair at each piece, ``row`` its text; a text's
    first piece pairs with 0.
    """

    def __init__(self, code: np.ndarray, row: np.ndarray, shards: int):
        before = np.zeros_like(code)
        before[1:] = np.where(row[1:] == row[:-1], code[:-1], 0)
        self.row = row
        pair, place, count = np.unique((before << np.uint64(32)) | code, return_inverse=True, return_counts=True)
        shard = (mix(pair >> np.uint64(32)) >> np.uint64(33)) % np.uint64(shards)
        order = np.argsort(shard, kind="stable")
        new = np.empty(len(order), np.int64)
        new[order] = np.arange(len(order))
        self.code, self.count, self.place = pair[order], count[order], new[place]
        self.edge = np.searchsorted(shard[order], np.arange(shards + 1))

    def firsts(self) -> np.ndarray:
        """Where the pairs of each first piece begin."""
        head = self.code >> np.uint64(32)
        return np.flatnonzero(np.append(True, head[1:] != head[:-1])[: len(head)])

    def bits(self, totals: np.ndarray, follows: np.ndarray, cut: tuple[float, float, float], base: np.ndarray) -> np.ndarray:
        """Bits of each piece without its own text's pairs.

        ``totals`` are the counts of the distinct pairs over all texts; ``follows`` are, for each first
        piece, the sum of its pairs and how many of them have the count one, two, three or more;
        ``base`` is each piece's own probability.
        """
        first = self.firsts()
        head = np.repeat(np.arange(len(first)), np.diff(np.append(first, len(self.code))))
        texts = int(self.row[-1]) + 1
        own, at, n = np.unique(self.place * texts + self.row, return_inverse=True, return_counts=True)
        pair, text = own // texts, own % texts
        left = totals[pair] - n
        _, context = np.unique(head[pair] * texts + text, return_inverse=True)
        size = int(context.max()) + 1
        above = np.empty(size, np.int64)
        above[context] = head[pair]
        total = follows[0][above] - np.bincount(context, n, size)
        reserve = np.zeros(size)
        for k in (1, 2, 3):
            old, new = np.minimum(totals[pair], 3) == k, np.minimum(left, 3) == k
            reserve += cut[k - 1] * (follows[k][above] + np.bincount(context, new.astype(float) - old, size))
        weight = np.where(total > 0, reserve / np.maximum(total, 1), 1.0)
        known = np.maximum(left - np.array([0.0, *cut])[np.minimum(left, 3)], 0) / np.maximum(total, 1)[context]
        return -np.log2(known[at] + weight[context][at] * base)


def _texts(table: pa.Table, bits: list[np.ndarray] | None = None) -> Iterator[tuple[str, np.ndarray, np.ndarray, np.ndarray]]:
    """For each language of a part: the rows and codes of its pieces, and the sum of ``bits`` (of each byte) over each piece."""
    langs = np.array([x or "" for x in table["lang"].to_pylist()], object)
    row, code, own = [np.zeros(0, np.int64)], [np.zeros(0, np.uint64)], [np.zeros(0)]
    for k, (first, _, buffer, starts) in enumerate(text_slices(table["text"], GAP)):
        at, found = pieces(buffer)
        text = np.searchsorted(starts, at, side="right") - 1
        row.append(first + text)
        code.append(found)
        if bits:
            total = np.concatenate([[0.0], np.cumsum(bits[k], dtype=np.float64)])
            own.append(total[np.minimum(np.append(at[1:], len(buffer)), starts[text + 1])] - total[at])
        else:
            own.append(np.zeros(len(at)))
    row, code, own = (np.concatenate(x) for x in (row, code, own))
    for lang in sorted(set(langs)):
        mine = np.flatnonzero((langs == lang)[row])
        if len(mine):
            yield lang, row[mine], code[mine], own[mine]


def _gathered(batches: Iterator[pa.RecordBatch], part_bytes: int) -> Iterator[tuple[int, pa.Table]]:
    """Parts of about ``part_bytes`` of text, numbered."""
    number = TaskContext.get().partitionId() << 32
    held, size = [], 0
    for batch in light_batches(batches, limit=part_bytes // 2):
        held.append(batch)
        size += column(batch, "text").nbytes
        if size >= part_bytes:
            yield number, pa.Table.from_batches(held).combine_chunks()
            held, size, number = [], 0, number + 1
    if held:
        yield number, pa.Table.from_batches(held).combine_chunks()


def _closed(part: tuple[int, pa.Table]) -> pa.RecordBatch:
    """A part as one compressed value."""
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, part[1].schema, options=pa.ipc.IpcWriteOptions(compression=pa.Codec("zstd", compression_level=6))) as out:
        out.write_table(part[1])
    return pa.RecordBatch.from_arrays([pa.array([part[0]], pa.int64()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], names=["part", "rows"])


def _opened(rows: Iterable[pa.Scalar]) -> pa.Table:
    return pa.concat_tables([pa.ipc.open_stream(x.as_buffer()).read_all() for x in rows]).combine_chunks()


def _pairing(parts: Iterator[tuple[int, pa.Table]], shards: int) -> Iterator[pa.RecordBatch]:
    for part, table in parts:
        rows = []
        for lang, row, code, _ in _texts(table):
            found = Pairs(code, row, shards)
            for s, (a, b) in enumerate(zip(found.edge[:-1].tolist(), found.edge[1:].tolist(), strict=True)):
                if b > a:
                    rows.append((part, lang, s, packed(np.diff(found.code[a:b], prepend=np.uint64(0)).view(np.int64)), packed(found.count[a:b])))
        yield from _table(rows, "part long, lang string, shard int, pairs binary, counts binary").to_batches()


KINDS = {"long": pa.int64(), "int": pa.int32(), "string": pa.string(), "binary": pa.binary()}


def _table(rows: list[tuple], schema: str) -> pa.Table:
    names, kinds = zip(*(f.split() for f in schema.split(", ")), strict=True)
    columns = list(zip(*rows, strict=True)) if rows else [[]] * len(names)
    return pa.table([pa.array(c, KINDS[k]) for c, k in zip(columns, kinds, strict=True)], names=list(names))


ANSWER = "part long, lang string, shard int, totals binary, follows binary, n1 long, n2 long, n3 long, n4 long"


def _answer(asked: pa.Table) -> pa.Table:
    """The counts of a shard's pairs over all parts, for each part in the order in which it sent them; one more row counts the counts."""
    own = [np.cumsum(unpacked(x.as_py()).view(np.uint64)) for x in asked["pairs"]]
    counts = np.concatenate([unpacked(x.as_py()) for x in asked["counts"]])
    code, place = np.unique(np.concatenate(own), return_inverse=True)
    total = np.bincount(place, counts).astype(np.int64)
    head = code >> np.uint64(32)
    first = np.flatnonzero(np.append(True, head[1:] != head[:-1]))
    follows = [np.add.reduceat(total, first)] + [np.add.reduceat((np.minimum(total, 3) == k).astype(np.int64), first) for k in (1, 2, 3)]
    lang, shard = asked["lang"][0].as_py(), asked["shard"][0].as_py()
    rows, at = [(-1, lang, shard, None, None, *(int((total == k).sum()) for k in (1, 2, 3, 4)))], 0
    group = np.searchsorted(first, np.arange(len(code)), side="right") - 1
    for part, mine in zip(asked["part"].to_pylist(), own, strict=True):
        where = place[at : at + len(mine)]
        at += len(mine)
        met = group[where]
        met = met[np.append(True, met[1:] != met[:-1])]
        rows.append((part, lang, shard, packed(total[where]), packed(np.concatenate([f[met] for f in follows])), 0, 0, 0, 0))
    return _table(rows, ANSWER)


def _scoring(shared, cuts: dict[str, tuple[float, float, float]], keep: list[str], shards: int):
    lookups: dict[str, _Lookup] = {}

    def run(part: pa.Table, answers: pa.Table) -> pa.Table:
        table = _opened(part["rows"])
        if not lookups:
            lookups.update({lang: _Lookup(model) for lang, model in shared.value.items()})
        bits: list[np.ndarray] = []
        out = pa.Table.from_batches(_measuring(lookups, keep, bits)(table.to_batches()))
        said: dict[str, list] = {}
        for lang, shard, totals, follows in zip(*(answers[c].to_pylist() for c in ("lang", "shard", "totals", "follows")), strict=True):
            said.setdefault(lang, []).append((shard, totals, follows))
        spent = np.zeros(table.num_rows)
        for lang, row, code, own in _texts(table, bits):
            found = Pairs(code, row, shards)
            got = sorted(said.get(lang, []))
            totals = np.concatenate([np.zeros(0, np.int64), *(unpacked(t) for _, t, _ in got)])
            follows = np.hstack([np.zeros((4, 0), np.int64), *(unpacked(f).reshape(4, -1) for _, _, f in got)])
            if len(totals) != len(found.code) or follows.shape[1] != len(found.firsts()):
                raise RuntimeError("a part has other rows than were counted: its input is not repeatable")
            spent += np.bincount(row, found.bits(totals, follows, cuts[lang], np.exp2(-np.minimum(own, 200.0))), len(spent))
        give_back()
        return out.append_column(MEASURES[-1], pa.array(spent / np.maximum(1, _sizes(table))))

    return run


def _sizes(table: pa.Table) -> np.ndarray:
    return pc.fill_null(pc.binary_length(table["text"]), 0).to_numpy().astype(np.int64)


def _measuring(lookups: dict[str, _Lookup], keep: list[str], every: list[np.ndarray]):
    """The base measures and bits a character; ``every`` gets the bits of each byte."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            langs = column(batch, "lang").to_pylist()
            out: dict[str, list[np.ndarray]] = {k: [] for k in MEASURES[:-1]}
            for first_row, rows, buffer, starts in text_slices(column(batch, "text"), GAP):
                words, at, first = split_words(buffer, starts)
                data = np.frombuffer(buffer, np.uint8)
                points = (data & 0xC0) != 0x80
                space = CLASS[data] == 0
                out["n_words"].append(np.diff(first))
                out["word_chars"].append(np.add.reduceat(points & ~space, starts[:-1], dtype=np.int64))
                out["n_symbols"].append(np.add.reduceat(np.isin(data, SYMBOLS), starts[:-1], dtype=np.int64))
                out["n_repeat_words"].append(repeated_trigram_words(word_hashes(words), first))
                dup = []
                for a, b in zip(starts[:-1].tolist(), (starts[1:] - len(GAP)).tolist(), strict=True):
                    lines = [x for x in buffer[a:b].split(b"\n") if x.strip()]
                    dup.append(len(lines) - len(set(lines)))
                out["n_dup_lines"].append(np.array(dup, np.int64))
                grams = packed_grams(buffer)
                bits = np.zeros(len(grams), np.float32)
                size = np.diff(starts)
                own = np.array([x or "" for x in langs[first_row : first_row + rows]], object)
                for lang in set(own):
                    if lang in lookups:
                        mine = np.repeat(own == lang, size)
                        bits[mine] = lookups[lang](grams[mine])
                ends = starts[1:] - len(GAP)
                bits[np.repeat(ends, len(GAP)) + np.tile(np.arange(len(GAP)), rows)] = 0
                every.append(bits)
                out["bits_per_char"].append(np.add.reduceat(bits, starts[:-1], dtype=np.float64) / np.maximum(1, size - len(GAP)))
            group = pa.array([x or "" for x in langs], pa.string())
            arrays = [pa.array(np.concatenate(v) if v else np.zeros(0)).cast(pa.float64() if k == "bits_per_char" else pa.int64()) for k, v in out.items()]
            yield pa.RecordBatch.from_arrays([*[column(batch, c) for c in keep], group, *arrays], names=[*keep, "lang_group", *out])

    return run


def train(docs: DataFrame) -> dict[str, KneserNey]:
    """A character model for each language, from counts over all texts: at most 2**24 rows of 16 bytes a language, as arrays."""
    found = gram_counts(docs).toArrow()
    lang = np.array(found["lang"].to_pylist(), object)
    gram, n = found["gram"].to_numpy(), found["n"].to_numpy()
    return {x: KneserNey(gram[lang == x], n[lang == x]) for x in sorted(set(lang))}


def text_digest() -> Column:
    return F.unhex(F.md5(F.coalesce("text", F.lit("")).cast("binary")))


def judge(docs: DataFrame, spread: float = 3.0, keep: list[str] | None = None, part_bytes: int = PART_BYTES) -> DataFrame:
    """Per row: the columns ``keep``, lang_group, text_digest, n_words, the base measures, bits_per_char, piece_bits_per_char, base_failed and kept.

    The base rules fail texts of under 50 words and those where more than half of the words stand in
    repeated three-word windows. ``kept`` is the same for rows of the same text and language.
    """
    keep = ["doc_id"] if keep is None else keep
    docs = without(docs, *ADDED)
    spark = docs.sparkSession
    docs = docs.select(*dict.fromkeys([*keep, "text", "lang"]))
    docs = docs if repeatable(docs) else staged(docs, "documents")
    shared = spark.sparkContext.broadcast(train(docs))
    carried = [*keep, "text_digest"]
    kinds = "".join(f"`{k}` {docs.schema[k].dataType.simpleString()}, " for k in keep)
    schema = f"{kinds}text_digest binary, lang_group string, {', '.join(f'{m} long' for m in MEASURES[:-2])}, bits_per_char double, piece_bits_per_char double"
    shards = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")) // TO_A_SHARD)
    rows = docs.withColumn("text_digest", text_digest())

    def gather(batches):
        return map(_closed, _gathered(batches, part_bytes))

    def pair(batches):
        return _pairing(_gathered(batches, part_bytes), shards)

    asked = rows.mapInArrow(tidy(pair), "part long, lang string, shard int, pairs binary, counts binary")
    parts = rows.mapInArrow(tidy(gather), "part long, rows binary")  # the same parts again, as the input is repeatable
    answers = staged(asked.groupBy("lang", "shard").applyInArrow(_answer, ANSWER), "answers")
    counts = answers.where("part < 0").groupBy("lang").agg(*[F.sum(f"n{k}") for k in (1, 2, 3, 4)]).collect()  # a row a language
    cuts = {r[0]: discounts(*r[1:]) for r in counts}
    measured = parts.groupBy("part").cogroup(answers.where("part >= 0").groupBy("part")).applyInArrow(_scoring(shared, cuts, carried, shards), schema)
    measured = staged(measured, "measured")
    measured = measured.withColumn("base_failed", (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words")))
    scores = MEASURES[-2:]
    texts = measured.where("not base_failed").groupBy("lang_group", "text_digest").agg(*[F.min(c).alias(c) for c in scores])
    bands = texts.groupBy("lang_group").agg(*[F.percentile_approx(c, [0.25, 0.75], 10_000).alias(q) for c, q in zip(scores, ("q", "w"), strict=True)])
    width = F.greatest(F.col("q")[1] - F.col("q")[0], F.lit(LEAST_SPREAD))
    above = F.col("w")[1] + spread * F.greatest(F.col("w")[1] - F.col("w")[0], F.lit(LEAST_SPREAD))
    bands = bands.select("lang_group", (F.col("q")[0] - spread * width).alias("low"), (F.col("q")[1] + spread * width).alias("high"), above.alias("above"))
    judged = measured.join(F.broadcast(bands), "lang_group", "left")  # a row a language
    inside = F.coalesce(F.col("bits_per_char").between(F.col("low"), F.col("high")) & (F.col("piece_bits_per_char") <= F.col("above")), F.lit(True))
    return judged.withColumn("kept", ~F.col("base_failed") & inside).drop("low", "high", "above")
