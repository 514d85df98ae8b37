"""SentencePiece encoding and decoding with N-best segmentations.

The lattice of a text has an edge for every vocabulary piece that matches a stretch of it, and for every character
without a piece one edge of its UTF-8 byte pieces. Forward Viterbi gives the best score from the start to each
place. The N best paths come out of a backward A-star search from the end, whose heuristic is that forward score:
it is exact, so paths leave the agenda in order and only nodes of returned paths are expanded.

No piece crosses certain pairs of characters (before a blank, around a line end, and any pair that no piece holds),
so the lattice of a text is a chain of independent lattices. The short ones that a slice of rows holds are searched
together, in step (``lattices``), and remembered within a bound; a long unbroken run is searched by itself, in time that
grows with its length. The N best of a text are combined from the N best of its parts by the same best-first rule.
The score is the sum of the pieces' scores. A blank is the mark U+2581, and a text starts with one; a mark
that the text itself holds is written as bytes, so decoding always returns the text.

Null and empty texts have no piece and score 0. Equal scores keep the order of discovery, which depends on the text
alone. Repeated rows encode alike, and once where they stand together.
"""

from __future__ import annotations

import heapq
import re
from array import array
from bisect import bisect_right, insort
from functools import cached_property
from itertools import chain, islice
from operator import itemgetter

import numpy as np
import pyarrow as pa
import sentencepiece
import xxhash
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import lattices
from .common import _caches, documents, map_rows, tokenizer_file

MODEL, NBEST = "piece_bpe_32k.model", 2
#: Chunks of one generation of remembered ones; longest that is remembered and searched in step, in characters.
CHUNKS, LONGEST = 60_000, 48
#: Rows whose chunks are searched together, by the query alone and beside a pipeline's other memory; most characters of texts that are
#: cut into chunks at once, and of new chunks that are searched in step at once.
TOGETHER, FEWER = 512, 256
CUT, STEPPED = 1 << 21, 1 << 16
INFINITE = float("inf")
MARK = "▁"
_FAST = re.compile(rf"{MARK}*[^{MARK}\n]+|{MARK}+|\n")


def combined(parts: list[list[float]], n: int) -> list[tuple[float, tuple[int, ...]]]:
    """N best sums of one choice from each part, as (what it loses against all first choices, choices); the scores of a
    part fall."""
    loss = lambda pick: sum([p[0] - p[k] for p, k in zip(parts, pick) if k])
    start = (0,) * len(parts)
    agenda, seen, out = [(0.0, start)], {start}, []
    while agenda and len(out) < n:
        lost, pick = heapq.heappop(agenda)
        out.append((lost, pick))
        for j, k in enumerate(pick):
            if k + 1 < len(parts[j]):
                more = (*pick[:j], k + 1, *pick[j + 1 :])
                if more not in seen:
                    seen.add(more)
                    heapq.heappush(agenda, (loss(more), more))
    return out


class Pieces:
    """A vocabulary, ready to encode. ``model`` is the content of a .model file."""

    def __init__(self, model: bytes, nbest: int = NBEST):
        sp = sentencepiece.SentencePieceProcessor(model_proto=model)
        self.nbest, size = nbest, sp.get_piece_size()
        self.score: dict = {}
        self.text: list[bytes] = [b""] * size
        self.byte = [0] * 256
        for i in range(size):
            piece = sp.id_to_piece(i)
            if sp.is_byte(i):
                self.byte[int(piece[3:5], 16)] = i
                self.text[i] = bytes([int(piece[3:5], 16)])
            elif not (sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i)):
                self.score[piece] = (sp.get_score(i), i)
                self.text[i] = piece.replace(MARK, " ").encode()
        self.glue = {a + b for p in self.score for a, b in zip(p, p[1:])}
        self.unknown = -float(size) - 10.0
        self.fast = not any(g[1] == MARK and g[0] != MARK or "\n" in g for g in self.glue)
        self.mark = ((self.unknown * 3, np.array([self.byte[b] for b in MARK.encode()], "<i4").tobytes()),)
        self.longest = max(map(len, self.score), default=1)
        self.chunk: dict[str, tuple] = {}
        self.old: dict[str, tuple] = {}
        _caches.append(self)
        self.flat = lattices.Trie({p: i for p, (_, i) in self.score.items()})
        self.weights = np.zeros(size)
        for w, i in self.score.values():
            self.weights[i] = w

    @cached_property
    def trie(self) -> dict:
        """The pieces by character, for single searches; made when a long run first needs one."""
        root: dict = {}
        for piece, (w, i) in self.score.items():
            node, entry = root, None
            for c in piece:
                entry = node.setdefault(c, [{}, None])
                node = entry[0]
            entry[1] = (w, (i,))
        return root

    def clear(self) -> None:
        self.chunk, self.old = {}, {}

    def lattice(self, s: str) -> tuple[list[list[tuple[int, float, tuple[int, ...]]]], list[float]]:
        """For each place the edges that end there (start, score, ids), and the best score from the start to it."""
        n, longest = len(s), self.longest
        edges: list = [[] for _ in range(n + 1)]
        ahead = [0.0] + [-INFINITE] * n
        for i in range(n):
            node, found = self.trie, []
            for j, c in enumerate(s[i : i + longest], i + 1):
                step = node.get(c)
                if step is None:
                    break
                node, hit = step
                if hit is not None:
                    found.append((j, *hit))
            if not found or found[0][0] > i + 1:
                raw = s[i].encode("utf-8", "replace")
                found.append((i + 1, self.unknown * len(raw), tuple(self.byte[b] for b in raw)))
            for j, w, ids in found:
                edges[j].append((i, w, ids))
                ahead[j] = max(ahead[j], ahead[i] + w)
        return edges, ahead

    def search(self, s: str, n: int) -> list[tuple[float, tuple[int, ...]]]:
        """The N best (score, ids) of one lattice of any length.

        An entry of the agenda is a path from the end back to a place, with what it loses against the best score: the
        forward score of that place completes it exactly, so the least loss is the next best path. Taking an entry
        follows its lossless edges to the start and enters the other edges on the way; as each entry is one path at
        least, only as many of least loss as are still wanted are kept.
        """
        edges, ahead = self.lattice(s)
        agenda, out, turn = [(0.0, 0, len(s), None)], [], 0
        while agenda and len(out) < n:
            lost, _, at, path = agenda.pop(0)
            wanted = n - len(out) - 1
            while at:
                here, way = ahead[at], None
                for i, w, ids in edges[at]:
                    gap = here - (ahead[i] + w)
                    if way is None and gap == 0.0:
                        way = i, ids
                    elif wanted and (len(agenda) < wanted or lost + gap < agenda[-1][0]):
                        turn += 1
                        insort(agenda, (lost + gap, turn, i, (ids, path)))
                        del agenda[wanted:]
                at, path = way[0], (way[1], path)
            found: list[int] = []
            while path is not None:
                found += path[0]
                path = path[1]
            out.append((ahead[len(s)] - lost, tuple(found)))
        return out

    def _cut(self, s: str) -> list[str]:
        """Parts that no piece crosses."""
        cuts = [0, *[i for i in range(1, len(s)) if s[i - 1 : i + 1] not in self.glue], len(s)]
        return [s[a:b] for a, b in zip(cuts, cuts[1:])]

    def _short(self, chunks: list[str]) -> dict[str, tuple[tuple[float, bytes], ...]]:
        """The N best (score, ids) of each of some different short chunks, shortest first, searched in step. Lattices take some hundred
        bytes a character, so ``STEPPED`` characters at once bound memory; as chunks are sorted, each search has few steps besides."""
        found: dict[str, tuple[tuple[float, bytes], ...]] = {}
        parts = np.cumsum(np.fromiter(map(len, chunks), np.int64, len(chunks))) // STEPPED
        edges = [0, *(np.flatnonzero(np.diff(parts)) + 1).tolist(), len(chunks)]
        for a, b in zip(edges, edges[1:]):
            if a < b:
                found |= self._stepped(chunks[a:b])
        return found

    def _stepped(self, chunks: list[str]) -> dict[str, tuple[tuple[float, bytes], ...]]:
        ranks = []
        for scores, pieces, counts in lattices.nbest(self.flat, self.weights, self.unknown, chunks, self.nbest):
            plain = pieces < len(self.weights)
            spelled = [[self.byte[b] for b in chr(c).encode("utf-8", "replace")] for c in (pieces[~plain] - len(self.weights)).tolist()]
            size = np.ones(len(pieces), np.int64)
            size[~plain] = [len(x) for x in spelled]
            ids = np.repeat(pieces, size)
            ids[np.repeat(~plain, size)] = [i for x in spelled for i in x]
            ends = (4 * np.append(0, np.cumsum(size))[np.append(0, np.cumsum(counts))]).tolist()
            data = ids.astype("<i4").tobytes()
            ranks.append(zip(scores.tolist(), [data[a:b] for a, b in zip(ends, ends[1:])]))
        found = dict(zip(chunks, zip(*ranks)))
        for c, paths in found.items():
            if paths[-1][0] == -INFINITE:
                found[c] = tuple(p for p in paths if p[0] > -INFINITE)
        return found

    def _long(self, s: str) -> tuple[tuple[float, bytes], ...]:
        """The N best (score, ids) of a chunk of any length: of its parts, and a long part by itself."""
        parts = self._cut(s)
        known = self._short(sorted((p for p in dict.fromkeys(parts) if len(p) <= LONGEST), key=len))
        for p in dict.fromkeys(parts):
            if len(p) > LONGEST:
                known[p] = tuple((w, array("i", ids).tobytes()) for w, ids in self.search(p, self.nbest))
        return tuple(self._joined([parts], known)[0])

    def _known(self, wanted: set[str]) -> dict[str, tuple[tuple[float, bytes], ...]]:
        """The N best of each chunk. Short chunks that aren't remembered are searched together. Two generations of at most
        ``CHUNKS`` are remembered, no chunk longer than ``LONGEST``, so memory is bounded."""
        known = {c: self.chunk[c] for c in wanted & self.chunk.keys()}
        known |= {c: self.old[c] for c in (wanted - known.keys()) & self.old.keys()}
        new = sorted(wanted - known.keys(), key=len)
        short = bisect_right(new, LONGEST, key=len)
        known |= self._short(new[:short])
        if len(self.chunk) + len(known) > CHUNKS:
            self.old, self.chunk = self.chunk, {}
        self.chunk |= known if len(known) <= CHUNKS else dict(islice(known.items(), CHUNKS))
        for c in new[short:]:
            known[c] = self._long(c)
        return known

    def _joined(self, runs: list[list[str]], known: dict[str, tuple[tuple[float, bytes], ...]]) -> list[list[tuple[float, bytes]]]:
        """The N best (score, ids) of each run of chunks; no run is empty.

        All runs stand in flat arrays. A run's N best differ from its best in the N - 1 chunks that lose least by their
        second choice, at most; these are found for all runs at once, and only they are combined run by run.
        """
        names = list(known)
        number = dict(zip(names, range(len(names))))
        at = np.fromiter(map(number.__getitem__, chain.from_iterable(runs)), np.int64)
        sizes = np.fromiter(map(len, runs), np.int64)
        heads = np.cumsum(sizes) - sizes
        found = [known[c] for c in names]
        score = np.array([f[0][0] for f in found])
        loss = np.array([f[0][0] - f[1][0] if len(f) > 1 else INFINITE for f in found])
        first = [f[0][1] for f in found]
        bytes_ = np.fromiter(map(len, first), np.int64)
        ends = np.append(0, np.cumsum(bytes_[at]))
        data = b"".join(map(first.__getitem__, at.tolist()))
        total = np.add.reduceat(score[at], heads)
        least, whose = loss[at], np.repeat(np.arange(len(runs)), sizes)
        loose = []  # places of the chunks that lose least, for each run; -1 where there is no further
        for _ in range(self.nbest - 1):
            low = np.minimum.reduceat(least, heads)
            hit = np.flatnonzero((least == low[whose]) & (least < INFINITE))
            hit = hit[np.append(True, whose[hit[1:]] != whose[hit[:-1]])] if len(hit) else hit
            place = np.full(len(runs), -1)
            place[whose[hit]] = hit
            loose.append(place)
            least[hit] = INFINITE
        out = []
        for k, (best, head, size) in enumerate(zip(total.tolist(), heads.tolist(), sizes.tolist())):
            begin, end = int(ends[head]), int(ends[head + size])
            places = sorted(int(x[k]) for x in loose if x[k] >= 0)
            parts = [found[at[p]] for p in places]
            row = []
            for lost, pick in combined([[w for w, _ in p] for p in parts], self.nbest):
                got, done = [], begin
                for p, part, choice in zip(places, parts, pick):
                    if choice:
                        got += [data[done : int(ends[p])], part[choice][1]]
                        done = int(ends[p + 1])
                row.append((best - lost, b"".join([*got, data[done:end]])))
            out.append(row)
        return out

    def many(self, texts: list[str | None]) -> list[list[tuple[float, bytes]]]:
        """The N best (score, ids as little-endian int32) of each text, best first; fewer where it has fewer segmentations. Equal texts
        are encoded once."""
        found: dict[str | None, list[tuple[float, bytes]]] = {}
        part, held = [], 0
        for t in dict.fromkeys(texts):
            if not t:
                found[t] = [(0.0, b"")]
                continue
            if held + len(t) > CUT and part:
                found |= self._each(part)
                part, held = [], 0
            part.append(t)
            held += len(t)
        if part:
            found |= self._each(part)
        return [found[t] for t in texts]

    def _each(self, texts: list[str]) -> dict[str, list[tuple[float, bytes]]]:
        """The N best of some different texts, none empty."""
        cut = [self.runs(t) for t in texts]
        known = self._known(set().union(*cut) - {None})
        known[None] = self.mark
        return dict(zip(texts, self._joined(cut, known)))

    def runs(self, text: str) -> list[str | None]:
        """Chunks of a text in order; None stands for a mark in the text itself."""
        out: list = []
        for k, run in enumerate(text.split(MARK)):
            if k:
                out.append(None)
            s = ("" if k else MARK) + run.replace(" ", MARK)
            out += _FAST.findall(s) if self.fast else [s] if s else []
        return out

    def best(self, text: str | None) -> list[tuple[float, bytes]]:
        """The N best (score, ids as little-endian int32) of a text."""
        return self.many([text])[0]

    def encode(self, text: str | None) -> tuple[bytes, float, float]:
        """(ids as little-endian int32, score, score of the second best; -inf if there is none) of a text."""
        got = self.best(text)
        return got[0][1], got[0][0], got[1][0] if len(got) > 1 else float("-inf")

    def encode_nbest(self, text: str | None) -> list[tuple[float, list[int]]]:
        """The N best (score, ids) of a whole text."""
        return [(score, np.frombuffer(ids, "<i4").tolist()) for score, ids in self.best(text)]

    def decode(self, ids) -> str:
        text = b"".join(itemgetter(*ids, 0, 0)(self.text)[:-2]).decode("utf-8", "replace")
        return text[1:] if text.startswith(" ") else text


_ready: dict[tuple[int, int], Pieces] = {}


def ready(model: bytes, nbest: int) -> Pieces:
    key = (xxhash.xxh64_intdigest(model), nbest)
    if key not in _ready:
        _ready[key] = Pieces(model, nbest)
    return _ready[key]


def _model(path: str) -> bytes:
    with open(path, "rb") as f:
        return f.read()


def ids_hash(ids: bytes) -> str:
    return f"{xxhash.xxh64_intdigest(ids):016x}"


def encoded(docs: DataFrame, path: str | None = None, nbest: int = NBEST, also: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, pieces, score, scores, ids_hashes): the best segmentation of every whole text, and the scores and hashes of
    the ids of all N best ones, best first. Columns named in ``also`` come along."""
    spark = docs.sparkSession
    sent = spark.sparkContext.broadcast(_model(path or tokenizer_file(spark, MODEL)))

    def rows(part: dict) -> dict:
        coder = ready(sent.value, nbest)
        first, scores, hashes = [], [], []
        for got in coder.many(part["text"]):
            first.append(got[0][1])
            scores.append([g[0] for g in got])
            hashes.append([ids_hash(g[1]) for g in got])
        ends = np.cumsum([0, *(len(x) // 4 for x in first)], dtype=np.int32)
        ids = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.frombuffer(b"".join(first), "<i4")))
        return {"doc_id": part["doc_id"], "pieces": ids, "score": [x[0] for x in scores], "scores": scores, "ids_hashes": hashes} | {n: part[n] for n in also}

    kinds = dict(docs.dtypes)
    return map_rows(docs.select("doc_id", "text", *also), rows, ", ".join(["doc_id bigint, pieces array<int>, score double, scores array<double>, ids_hashes array<string>", *(f"{n} {kinds[n]}" for n in also)]), step=FEWER)


def decoded(pieces: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, text) from (doc_id, pieces)."""
    spark = pieces.sparkSession
    sent = spark.sparkContext.broadcast(_model(path or tokenizer_file(spark, MODEL)))

    def rows(part: dict) -> dict:
        coder = ready(sent.value, NBEST)
        return {"doc_id": part["doc_id"], "text": [None if p is None else coder.decode(p) for p in part["pieces"]]}

    return map_rows(pieces.select("doc_id", "pieces"), rows, "doc_id bigint, text string")


def op6_piece_nbest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of every whole text and its two best segmentations: pieces, score and hash of the ids of each, and whether decoding
    each of them returns the text."""
    sent = spark.sparkContext.broadcast(_model(tokenizer_file(spark, MODEL)))

    def rows(part: dict) -> dict:
        coder = ready(sent.value, NBEST)
        out: dict = {n: [] for n in ("n_pieces", "score", "second_score", "ids_hash", "second_n_pieces", "second_ids_hash", "round_trip")}
        for t, got in zip(part["text"], coder.many(part["text"])):
            back = all(coder.decode(np.frombuffer(ids, "<i4").tolist()) == (t or "") for _, ids in got)
            (score, ids), (second, other) = got[0], got[1] if len(got) > 1 else (None, None)
            row = (len(ids) // 4, score, second, ids_hash(ids), None if other is None else len(other) // 4, None if other is None else ids_hash(other), back)
            for n, v in zip(out, row):
                out[n].append(v)
        return {"doc_id": part["doc_id"]} | out

    return map_rows(documents(spark, sf_dir).select("doc_id", "text"), rows, "doc_id bigint, n_pieces bigint, score double, second_score double, ids_hash string, second_n_pieces bigint, second_ids_hash string, round_trip boolean", step=TOGETHER)


def placed(docs: DataFrame) -> DataFrame:
    """(doc_id, text, file_no, row_no): the place of each row. Sorted by the last two, rows stand as they were written.

    Files of a Spark writer are numbered in the order of its partitions, and readers may take them in any order, so the
    number in a file's name and the row's index in the file tell the place; for a frame that isn't read from Parquet
    files, its own partitions and rows do.
    """
    try:
        meta = docs.metadataColumn("_metadata")
        name, row = meta["file_name"], meta["row_index"]
        found = docs.select("doc_id", "text", name.alias("name"), row.alias("row_no"))
        found.schema  # noqa: B018  resolves the columns
    except AnalysisException:
        return docs.select("doc_id", "text", F.spark_partition_id().cast("bigint").alias("file_no"), F.monotonically_increasing_id().alias("row_no"))
    part = lambda pattern: F.coalesce(F.regexp_extract("name", pattern, 1).try_cast("bigint"), F.lit(0))
    number = part(r"part-(\d+)") * 1_000_000 + part(r"-c(\d+)\.")
    return found.select("doc_id", "text", number.alias("file_no"), "row_no")


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The segmentations (see ``encoded``) of every document, with (file_no, row_no), by which they sort in training order. A mix repeats
    rows; repeats are brought together, where one search serves them all."""
    alike = F.xxhash64("doc_id", "text")
    return encoded(placed(docs).repartition(alike).sortWithinPartitions(alike), also=("file_no", "row_no"))
