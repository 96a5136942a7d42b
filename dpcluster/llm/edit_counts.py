"""Token counts that follow edits, with a segment tree of pre-tokens kept for each document.

The leaves of a tree are the chunks of the text that are encoded on their own; its nodes hold sums of
characters and of tokens.  ``build`` writes the leaves of every document as a table; ``apply_edits``
takes that table and a table of edits, and gives the table after them.  An edit descends by characters
to the chunks that it touches, takes one more before them as context, cuts the changed text anew until
an old boundary is met again, and adds the differences on the way up.  Only chunks that the cut gives
are encoded, those of many documents at once; a document without edits is not encoded at all.

Edits of a document: (start, end, text), in code points of the text as it was, not overlapping.

Defined results: null text is empty text with no tokens; an edit past the end of the text counts as
one at its end; edits of a document that is not there are ignored; rows that share an id are edited
alike, null ids among them; repeated rows are counted each; an empty table gives no rows; extra
columns are ignored.
"""

from __future__ import annotations

import itertools
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpcluster.llm import scratch, tokens

#: The standard edits: numbers become one digit, runs of marks become one, a closing note is added.
_NUMBERS, _MARKS = re.compile(r"[0-9][0-9.,-]{3,}"), re.compile(r"([!?*#$%&=_-])\1+")
NOTE = "\n[edited]"


def standard_edits(text: str) -> list[tuple[int, int, str]]:
    out = [(m.start(), m.end(), "0") for m in _NUMBERS.finditer(text)]
    taken = [(s, e) for s, e, _ in out]
    i = 0
    for m in _MARKS.finditer(text):
        while i < len(taken) and taken[i][1] <= m.start():
            i += 1
        if i == len(taken) or m.end() <= taken[i][0]:
            out.append((m.start(), m.end(), m[1]))
    return sorted(out) + [(len(text), len(text), NOTE)]


def _nodes(leaves: np.ndarray, size: int) -> list[int]:
    """All nodes of a tree: the root at 1, the children of i at 2i and 2i + 1."""
    out = np.zeros(2 * size, np.int64)
    out[size : size + len(leaves)] = leaves
    at = size
    while at > 1:
        out[at // 2 : at] = out[at : 2 * at : 2] + out[at + 1 : 2 * at : 2]
        at //= 2
    return out.tolist()


class CountTree:
    """Sums of characters and tokens over the chunks of one text.

    Edits cut the text at once, and leave the tokens of the leaves that they touch open until
    ``settle``, so that the new chunks of many trees can be encoded together."""

    def __init__(self, codec: tokens.Codec, text: str, chars: np.ndarray | None = None, counts: np.ndarray | None = None):
        if codec.kind == "words":
            raise ValueError("the tokenizer drops white space, so its chunks do not cover the text")
        self.codec, self.text = codec, text
        if chars is None:
            chunks = codec.chunks(text)
            known = codec.count_chunks(chunks)
            chars, counts = np.array([len(c) for c in chunks], np.int64), np.array([known[c] for c in chunks], np.int64)
        self.n_leaves = max(1, len(chars))
        self.size = 1 << (self.n_leaves - 1).bit_length()
        self.chars, self.toks = _nodes(chars, self.size), _nodes(counts, self.size)
        self.ends = np.cumsum(chars).tolist() or [0]  # of the leaves in the text as it was
        self.changed: dict[int, list[str]] = {}
        self.open: set[int] = set()
        self.encoded = 0

    @property
    def tokens(self) -> int:
        return self.toks[1]

    @property
    def length(self) -> int:
        return self.chars[1]

    def leaf(self, i: int) -> str:
        if i in self.changed:
            return "".join(self.changed[i])
        return self.text[self.ends[i - 1] if i else 0 : self.ends[i]]

    def find(self, at: int) -> tuple[int, int]:
        """The leaf that holds a character, and the characters before that leaf."""
        node, before = 1, 0
        while node < self.size:
            node *= 2
            if at - before >= self.chars[node]:
                before += self.chars[node]
                node += 1
        return node - self.size, before

    @staticmethod
    def _add(nodes: list[int], node: int, more: int) -> None:
        while more and node:
            nodes[node] += more
            node //= 2

    def edit(self, start: int, end: int, new: str) -> None:
        """Replaces characters."""
        start, end = min(start, self.length), min(end, self.length)
        first, before = (0, 0) if self.length == 0 else self.find(min(start, self.length - 1))
        first = min(first, self.n_leaves - 1)
        # one leaf of context, and more while that is white space, whose cut depends on what follows
        context = ""
        while first > 0 and not context.strip():
            first -= 1
            context = self.leaf(first)
            before -= len(context)
        last, here = first, before
        while last < self.n_leaves and here + self.chars[self.size + last] <= end:
            here += self.chars[self.size + last]
            last += 1
        # widen to the right until the cut of the changed text meets an old boundary
        margin, shift = 2, len(new) - (end - start)
        while True:
            stop = min(self.n_leaves, last + margin)
            old = "".join(map(self.leaf, range(first, stop)))
            text = old[: start - before] + new + old[end - before :]
            chunks = self.codec.chunks(text)
            if stop == self.n_leaves:
                break
            ends, total, met = list(itertools.accumulate(map(len, chunks))), before, -1
            # what follows the boundary must hold a mark or letter, else a run of white space may go on
            solid = before - shift + len(text.rstrip())
            for i in range(first, stop - 1):
                total += self.chars[self.size + i]
                if end < total < solid and total + shift - before in ends:
                    met = i
                    break
            if met >= 0:
                stop, chunks = met + 1, chunks[: ends.index(total + shift - before) + 1]
                break
            margin *= 2
        # one chunk a leaf, so that leaves stay small however many edits come
        for i in range(first, stop):
            at = i - first
            part = chunks[at : at + 1] if i < stop - 1 else chunks[at:]
            if part or self.chars[self.size + i]:
                self._add(self.chars, self.size + i, sum(map(len, part)) - self.chars[self.size + i])
                self.changed[i] = part
                self.open.add(i)
        self.encoded += len(chunks)

    def to_encode(self):
        """The chunks that settle needs."""
        return itertools.chain.from_iterable(self.changed[i] for i in self.open)

    def settle(self, known: dict[str, int] | None = None) -> None:
        """Numbers of tokens of the leaves that were left open, and the sums above them."""
        known = known if known is not None else self.codec.count_chunks(self.to_encode())
        for i in self.open:
            self._add(self.toks, self.size + i, sum(known[c] for c in self.changed[i]) - self.toks[self.size + i])
        self.open = set()

    def leaves(self) -> tuple[str, np.ndarray, np.ndarray]:
        """The text as it is now, and characters and tokens of its chunks."""
        text = "".join(map(self.leaf, range(self.n_leaves)))
        held = [i for i in range(self.n_leaves) if self.chars[self.size + i]]
        if any(len(self.changed.get(i, ())) > 1 for i in held):
            chunks = [c for i in held for c in self.changed.get(i, [self.leaf(i)])]
            known = self.codec.count_chunks(chunks)
            return text, np.array([len(c) for c in chunks], np.int64), np.array([known[c] for c in chunks], np.int64)
        return text, *(np.array([x[self.size + i] for i in held], np.int64) for x in (self.chars, self.toks))


def _trees(codec: tokens.Codec, texts: pa.Array):
    """Of a run of texts: characters and tokens of all chunks, and the chunks before each text."""
    if codec.kind == "words":
        raise ValueError("the tokenizer drops white space, so its chunks do not cover the text")
    data, offsets = tokens.flat(texts)
    got = codec.encode_flat(data, offsets)
    chars = np.add.reduceat(((data & 0xC0) != 0x80).astype(np.int64), got.starts) if len(got.starts) else got.counts
    return chars, got.counts, got.chunks_before.tolist()


def _counter(path: str, edits):
    fields = ("n_tokens", "n_chunks", "n_edits", "n_encoded", "n_tokens_edited")

    def run(batches):
        for batch, texts in tokens.text_rows(batches):
            codec = tokens.codec(path)
            chars, counts, ends = _trees(codec, texts)
            trees, rows = [], []
            for text, a, b in zip(texts.to_pylist(), ends, ends[1:]):
                tree, todo = CountTree(codec, text or "", chars[a:b], counts[a:b]), edits(text or "")
                rows.append([tree.tokens, b - a, len(todo)])
                for start, end, new in reversed(todo):  # from the end, so places stay as they were
                    tree.edit(start, end, new)
                tree.text = ""
                trees.append(tree)
            known = codec.count_chunks(itertools.chain.from_iterable(t.to_encode() for t in trees))
            for row, tree in zip(rows, trees):
                tree.settle(known)
                row += [tree.encoded, tree.tokens]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(c, pa.int64()) for c in zip(*rows))], names=["doc_id", *fields])

    return run


def _source(docs: DataFrame) -> DataFrame:
    scratch.share_code(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")


def count_with_edits(docs: DataFrame, tokenizer_file: str, edits=standard_edits) -> DataFrame:
    """Per document: tokens, chunks, edits, chunks encoded again, and tokens after the edits.

    edits: a function from the text to its edits.  Trees are built, edited and dropped in one pass, and
    nothing is shuffled; ``build`` and ``apply_edits`` keep them."""
    return _source(docs).mapInArrow(_counter(tokenizer_file, edits), "doc_id long, n_tokens long, n_chunks long, n_edits long, n_encoded long, n_tokens_edited long")


TREES = "doc_id long, text string, chars array<int>, tokens array<int>, n_tokens long"
_TREES = pa.schema([("doc_id", pa.int64()), ("text", pa.string()), ("chars", pa.list_(pa.int32())), ("tokens", pa.list_(pa.int32())), ("n_tokens", pa.int64())])


def build(docs: DataFrame, tokenizer_file: str) -> DataFrame:
    """The trees to keep: per document its text and the characters and tokens of its leaves, in order."""

    def run(batches):
        for batch, texts in tokens.text_rows(batches):
            chars, counts, ends = _trees(tokens.codec(tokenizer_file), texts)
            ends = np.array(ends, np.int32)
            sums = np.concatenate([[0], np.cumsum(counts)])[ends]
            lists = [pa.ListArray.from_arrays(pa.array(ends), pa.array(x.astype(np.int32))) for x in (chars, counts)]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), texts.cast(pa.string()).fill_null(""), *lists, pa.array(np.diff(sums))], schema=_TREES)

    return _source(docs).mapInArrow(run, TREES)


def apply_edits(trees: DataFrame, edits: DataFrame, tokenizer_file: str) -> DataFrame:
    """The trees after edits (doc_id, start, end, text), with how many chunks were encoded again.

    Edits of a document travel as one list; trees without edits pass through as they are."""
    listed = edits.groupBy(F.col("doc_id").cast("long").alias("__doc")).agg(F.sort_array(F.collect_list(F.struct("start", "end", "text"))).alias("edits"))
    held = trees.join(listed, F.col("doc_id").eqNullSafe(F.col("__doc")), "left").select(*_TREES.names, "edits")
    schema = _TREES.append(pa.field("n_encoded", pa.int64()))

    def run(batches):
        for batch in tokens.small_batches(batches):
            codec, rows = tokens.codec(tokenizer_file), batch.to_pylist()
            todo = [(r, CountTree(codec, r["text"], np.array(r["chars"], np.int64), np.array(r["tokens"], np.int64))) for r in rows if r["edits"]]
            for r, tree in todo:
                for e in reversed(r["edits"]):
                    tree.edit(e["start"], e["end"], e["text"] or "")
            known = codec.count_chunks(itertools.chain.from_iterable(t.to_encode() for _, t in todo))
            for r in rows:
                r["n_encoded"] = 0
            for r, tree in todo:
                tree.settle(known)
                text, chars, counts = tree.leaves()
                r |= {"text": text, "chars": chars.tolist(), "tokens": counts.tolist(), "n_tokens": tree.tokens, "n_encoded": tree.encoded}
            yield pa.RecordBatch.from_pylist([{k: r[k] for k in schema.names} for r in rows], schema=schema)

    scratch.share_code(trees.sparkSession)
    return held.mapInArrow(run, TREES + ", n_encoded long")
