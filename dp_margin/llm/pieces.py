"""SentencePiece encoding and decoding: Viterbi over a double-array trie of scored pieces.

The vocabulary file gives pieces and scores. A text gets a white-space marker before it and for every space; the best segmentation is the one with the
largest sum of log scores; characters that no piece covers fall back to byte pieces. Pieces never hold a marker after another character, so the
text falls apart before every marker that follows another character, and equal parts are segmented once.

The file's scores are merge ranks (a piece's score is minus its rank), so by default a piece's log score is that of a Zipf law over the ranks;
``scores="file"`` takes them as they are, which is right for a file with unigram log-probabilities.

Defined cases: a null or empty text has no ids and decodes to an empty text; texts decode to themselves, spaces at any end and line
breaks too, but for markers of their own, which decode to spaces; a segment of any length takes memory for its best path only; repeated rows and rows
that share a doc_id, or have none, encode alike; extra columns are kept by ``encode_stage``, whose own get underscores after them where a name
is taken; an empty table gives no rows.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import IdTable, bound_batches, free_name, table
from .neardup import runs

MARK = "▁"
#: Bytes of a worker's table of segments, and segments looked up at once.
TABLE_BYTES, SEGMENTS = 48 << 20, 1 << 18
#: Characters of one vectorised look-up.
RUN_CHARS = 1 << 17


class DoubleArray:
    """A trie of strings in two arrays: state s has a child by code c at base[s] + c if check[base[s] + c] == s."""

    def __init__(self, words: list[str], values: list[int]):
        chars = sorted({c for w in words for c in w})
        self.codes = {c: i + 1 for i, c in enumerate(chars)}
        self.table = np.zeros(max([0, *map(ord, chars)]) + 2, np.int32)
        for c, i in self.codes.items():
            self.table[ord(c)] = i
        kids: list[dict[int, int]] = [{}]
        value = [-1]
        for w, v in zip(words, values, strict=True):
            s = 0
            for c in w:
                k = self.codes[c]
                if k not in kids[s]:
                    kids[s][k] = len(kids)
                    kids.append({})
                    value.append(-1)
                s = kids[s][k]
            value[s] = v
        self._pack(kids, value)
        self.depth = max(map(len, words), default=0)

    def _pack(self, kids, value) -> None:
        span = len(self.codes) + 2
        size = 2 * len(kids) + 2 * span
        used = np.zeros(size, bool)
        base, check, val = np.zeros(size, np.int32), np.full(size, -1, np.int32), np.full(size, -1, np.int32)
        used[0] = True
        start: dict[int, int] = {}  # where the search for a place goes on, by number of children
        todo = [(0, 0)]
        for node, state in todo:
            codes = np.array(sorted(kids[node]))
            if not len(codes):
                continue
            kind, b = min(len(codes), 64), -1
            at = start.get(kind, 1)
            while b < 0:
                if at + 512 + 2 * span >= len(used):
                    more = len(used)
                    used = np.concatenate((used, np.zeros(more, bool)))
                    base = np.concatenate((base, np.zeros(more, np.int32)))
                    check, val = (np.concatenate((x, np.full(more, -1, np.int32))) for x in (check, val))
                free = np.flatnonzero(~used[at + codes[0] : at + codes[0] + 512]) + at
                fits = free[~used[free[:, None] + codes].any(1)] if len(codes) > 1 else free
                b = int(fits[0]) if len(fits) else -1
                at = b if b >= 0 else at + 512
            start[kind] = at
            base[state] = b
            for c in codes.tolist():
                used[b + c] = True
                check[b + c] = state
                val[b + c] = value[kids[node][c]]
                todo.append((kids[node][c], b + c))
        self.base, self.check, self.value = base, check, val

    def matches(self, points: np.ndarray, stops: np.ndarray):
        """(start, length, value) of every word of the trie at every place of an array of code points; none crosses its stop."""
        code = np.where(points < len(self.table) - 1, self.table[np.minimum(points, len(self.table) - 1)], 0)
        at = np.flatnonzero(code > 0)
        state = np.zeros(len(at), np.int32)
        for d in range(self.depth):
            c = code[at + d]
            to = self.base[state] + c
            ok = (c > 0) & (self.base[state] > 0)
            ok &= self.check[np.where(ok, to, 0)] == state
            at, state = at[ok], to[ok]
            if not len(at):
                return
            hit = self.value[state] >= 0
            yield at[hit], d + 1, self.value[state[hit]]
            go = at + d + 1 < stops[at]
            at, state = at[go], state[go]


class PieceModel:
    def __init__(self, path: str, scores: str = "zipf"):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        self.pieces = [sp.id_to_piece(i) for i in range(n)]
        plain = [i for i in range(n) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]
        self.byte = np.full(256, sp.unk_id(), np.int64)
        for i in range(n):
            if sp.is_byte(i):
                self.byte[int(self.pieces[i][3:5], 16)] = i
        self.score = np.zeros(n)
        if scores == "zipf":
            order = sorted(plain, key=lambda i: (-sp.get_score(i), i))
            norm = np.log(np.sum(1 / np.arange(1, len(order) + 1)))
            for rank, i in enumerate(order, 1):
                self.score[i] = -np.log(rank) - norm
        else:
            for i in plain:
                self.score[i] = sp.get_score(i)
        low = float(self.score[plain].min()) - 10.0
        #: What a character without a piece costs: less than any other way round it.
        self.unknown = low
        self.trie = DoubleArray([self.pieces[i] for i in plain], plain)
        special = {i for i in range(n) if sp.is_control(i) or sp.is_unknown(i)}
        self.is_byte = {int(i): b for b, i in enumerate(self.byte) if i != sp.unk_id()}
        if any(MARK in self.pieces[i].lstrip(MARK) for i in plain):
            raise ValueError("a piece holds a marker after another character")
        #: What each id decodes to.
        self.spelled = [b"" if i in special else bytes([self.is_byte[i]]) if i in self.is_byte else p.replace(MARK, " ").encode() for i, p in enumerate(self.pieces)]
        self.table = IdTable(TABLE_BYTES, np.int32)

    def _fallback(self, ch: str) -> list[int]:
        return [int(self.byte[x]) for x in ch.encode("utf-8", "surrogatepass")]

    def segment(self, parts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The best ids of all parts in a row, and the number of ids of each: all look-ups are vectorised, then one forward pass for all parts of a run."""
        ids, lengths = [np.zeros(0, np.int32)], [np.zeros(0, np.int64)]
        start = 0
        while start < len(parts):
            stop, chars = start, 0
            while stop < len(parts) and (stop == start or chars + len(parts[stop]) <= RUN_CHARS):
                chars += len(parts[stop])
                stop += 1
            found = self._long(parts[start]) if chars > RUN_CHARS else self._segment(parts[start:stop])
            ids.append(found[0].astype(np.int32)), lengths.append(found[1])
            start = stop
        return np.concatenate(ids), np.concatenate(lengths)

    def _matches(self, points: np.ndarray, stops: np.ndarray):
        """Matches (start, length, id) by start, shortest first, and the number of the first match of every place."""
        found = list(self.trie.matches(points, stops))
        begin = np.concatenate([f[0] for f in found]) if found else np.zeros(0, np.int64)
        size = np.concatenate([np.full(len(f[0]), f[1]) for f in found]) if found else np.zeros(0, np.int64)
        ids = np.concatenate([f[2] for f in found]).astype(np.int64) if found else np.zeros(0, np.int64)
        order = np.lexsort((size, begin))
        begin, size, ids = begin[order], size[order], ids[order]
        return size, ids, np.searchsorted(begin, np.arange(len(points) + 1))

    def _segment(self, parts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        points = _points("".join(parts))
        lengths = np.array([len(p) for p in parts])
        edge = np.concatenate(([0], np.cumsum(lengths)))
        n = len(points)
        size, ids, first = self._matches(points, np.repeat(edge[1:], lengths))
        # forward over places within the part, for all parts at once; long parts run on alone at the end
        best = np.full(n + len(parts) + 1, -np.inf)
        via = np.full(n + len(parts) + 1, -1, np.int64)  # the match that ends here; -1: the character fell back
        part_of = np.repeat(np.arange(len(parts)), lengths)
        slot = np.arange(n) + part_of  # a place's node; a part has one node more than characters
        best[edge[:-1] + np.arange(len(parts))] = 0.0
        scores = self.score[ids]
        live = np.flatnonzero(lengths > 0)
        t = 0
        wide = 48
        while len(live) > wide:
            at = edge[live] + t
            s = slot[at]
            now = best[s]
            step = now + self.unknown
            better = step > best[s + 1]
            best[s[better] + 1], via[s[better] + 1] = step[better], -1
            k, end = first[at], first[at + 1]
            while True:
                go = k < end
                if not go.any():
                    break
                kk, ss, nn = k[go], s[go], now[go]
                to, value = ss + size[kk], nn + scores[kk]
                better = value > best[to]
                best[to[better]], via[to[better]] = value[better], kk[better]
                k = k + 1
            t += 1
            live = live[lengths[live] > t]
        for p in live.tolist():
            lo, hi = int(edge[p]), int(edge[p + 1])
            f, a, z = (first[lo : hi + 1] - first[lo]).tolist(), int(first[lo]), int(first[hi])
            b, v = best[lo + p : hi + p + 1].tolist(), via[lo + p : hi + p + 1].tolist()
            self._forward(b, v, t, hi - lo, f, size[a:z].tolist(), scores[a:z].tolist(), a)
            via[lo + p : hi + p + 1] = v
        return self._traced(points, lengths, edge, ids, size, via)

    def _forward(self, b: list, v: list, t: int, stop: int, f: list, size: list, score: list, first: int) -> None:
        """Best sums b and their last matches v of the places after t, one place after another."""
        unknown = self.unknown
        for i in range(t, stop):
            now = b[i]
            if now + unknown > b[i + 1]:
                b[i + 1], v[i + 1] = now + unknown, -1
            for k in range(f[i], f[i + 1]):
                x = now + score[k]
                if x > b[i + size[k]]:
                    b[i + size[k]], v[i + size[k]] = x, k + first

    def _traced(self, points, lengths, edge, ids, size, via) -> tuple[np.ndarray, np.ndarray]:
        """Backwards from every part's end, for all parts at once."""
        at, part = lengths.astype(np.int64), np.flatnonzero(lengths > 0)
        rows, found = [], []
        while len(part):
            k = via[edge[part] + part + at[part]]
            rows.append(part)
            # a character that fell back is kept by its place, as a negative number
            found.append(np.where(k < 0, -(edge[part] + at[part]), ids[k] if len(ids) else 0))
            at[part] -= np.where(k < 0, 1, size[k] if len(ids) else 1)
            part = part[at[part] > 0]
        if not rows:
            return np.zeros(0, np.int32), np.zeros(len(lengths), np.int64)
        steps = np.repeat(np.arange(len(rows)), [len(r) for r in rows])
        row, out = np.concatenate(rows), np.concatenate(found)
        order = np.lexsort((-steps, row))
        row, out = row[order], out[order]
        if (out < 0).any():
            spelled = [self._fallback(chr(points[-x - 1])) if x < 0 else [x] for x in out.tolist()]
            row = np.repeat(row, [len(x) for x in spelled])
            out = np.array([i for x in spelled for i in x])
        return out, np.bincount(row, minlength=len(lengths))

    def _long(self, part: str) -> tuple[np.ndarray, np.ndarray]:
        """One part longer than a run: forward run by run, keeping only every place's last match, then back over them."""
        n, depth = len(part), max(1, self.trie.depth)
        piece, length = np.full(n + 1, -1, np.int32), np.ones(n + 1, np.int32)
        ahead = [0.0] + [-np.inf] * depth  # best sums of the run's first places
        for lo in range(0, n, RUN_CHARS // 4):
            width = min(n, lo + RUN_CHARS // 4) - lo
            points = _points(part[lo : lo + width + depth])
            size, ids, first = self._matches(points, np.full(len(points), len(points)))
            best, via = ahead + [-np.inf] * width, [-2] * (depth + 1 + width)
            self._forward(best, via, 0, width, first.tolist(), size.tolist(), self.score[ids].tolist(), 0)
            # places beyond the run get what is best so far; the next run may better it
            came = np.array(via[: n - lo + 1])
            at = np.flatnonzero(came > -2)
            k = came[at]
            piece[lo + at], length[lo + at] = (np.where(k < 0, -1, ids[k]), np.where(k < 0, 1, size[k])) if len(ids) else (-1, 1)
            ahead = best[width : width + depth + 1]
        out, i = [], n
        while i > 0:
            if piece[i] < 0:
                out += reversed(self._fallback(part[i - 1]))
                i -= 1
            else:
                out.append(int(piece[i]))
                i -= int(length[i])
        return np.array(out[::-1], np.int64), np.array([len(out)])

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids one after another, and the number of ids of each text; null counts as empty."""
        parts, counts = _parts(texts)
        ids, lengths = [np.zeros(0, np.int32)], [np.zeros(0, np.int64)]
        for lo in range(0, len(parts), SEGMENTS):
            coded = pc.dictionary_encode(parts.slice(lo, SEGMENTS))
            distinct = coded.dictionary.to_pylist()
            if self.table.full:
                self.table.clear()
            where = self.table.where
            fresh = [p for p in distinct if p not in where]
            if fresh:
                self.table.store(fresh, *self.segment([MARK + p.replace(" ", MARK) for p in fresh]))
            slots = np.fromiter((where[p] for p in distinct), np.int64, len(distinct))
            found = self.table.gather(slots[coded.indices.to_numpy()])
            ids.append(found[0]), lengths.append(found[1])
        total = np.concatenate(([0], np.cumsum(np.concatenate(lengths))))
        edge = np.concatenate(([0], np.cumsum(counts)))
        return np.concatenate(ids), np.diff(total[edge])

    def decode(self, ids) -> str:
        """Pieces joined, byte pieces as UTF-8, markers as spaces, and the first marker taken away."""
        raw = b"".join(map(self.spelled.__getitem__, ids))
        try:
            text = raw.decode()
        except UnicodeDecodeError:
            text = self._decode_broken(ids)
        return text[1:] if text.startswith(" ") else text

    def _decode_broken(self, ids) -> str:
        """Ids whose byte pieces are no UTF-8: each run of byte pieces is replaced on its own."""
        out, raw = [], bytearray()
        for i in ids:
            if i in self.is_byte:
                raw.append(self.is_byte[i])
                continue
            out += [raw.decode("utf-8", "replace"), self.spelled[i].decode()]
            raw.clear()
        return "".join([*out, raw.decode("utf-8", "replace")])


def _points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)


def _parts(texts: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """Texts cut before every marker that follows another character, the first marker of each part left out, and the number of parts of each text.

    A part is a word with the spaces before it, but for the one that every word has; an empty text has no part.
    """
    texts = pc.fill_null(texts, "")
    words = pc.split_pattern(texts, " ")
    counts = pc.list_value_length(words).to_numpy(zero_copy_only=False).astype(np.int64)
    flat = words.flatten()
    last = np.zeros(len(flat), bool)
    last[np.cumsum(counts) - 1] = True
    keep = (pc.binary_length(flat).to_numpy(zero_copy_only=False) > 0) | last
    owner = np.repeat(np.arange(len(texts)), counts)
    keep &= (pc.binary_length(texts).to_numpy(zero_copy_only=False) > 0)[owner]
    if keep.all():
        return flat, counts
    at = np.flatnonzero(keep)
    begin = (np.cumsum(counts) - counts)[owner[at]]
    # dropped words between a kept one and the kept one, or the text's begin, before it
    before = np.concatenate(([-1], at[:-1]))
    gap = at - np.maximum(before, begin - 1) - 1
    flat = flat.take(pa.array(at))
    if gap.any():
        flat = pc.binary_join_element_wise(pc.binary_repeat(pa.array([" "]).take(pa.array(np.zeros(len(at), np.int64))), pa.array(gap)), flat, "")
    return flat, np.bincount(owner[at], minlength=len(texts)).astype(np.int64)


_MADE: dict[tuple[str, str], PieceModel] = {}


def model(path: str, scores: str = "zipf") -> PieceModel:
    if (path, scores) not in _MADE:
        _MADE[path, scores] = PieceModel(path, scores)
    return _MADE[path, scores]


def vocabulary(name: str = "piece_bpe_32k.model") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def added_names(docs: DataFrame) -> list[str]:
    """Names of the columns that ``encode_stage`` adds to docs."""
    return [free_name(docs, c) for c in ("dm_ids", "dm_n_tokens", "dm_ids_crc32", "dm_decoded")]


def encode_stage(docs: DataFrame, path: str | None = None, scores: str = "zipf") -> DataFrame:
    """docs with dm_ids (array<int>), dm_n_tokens, dm_ids_crc32 (of little-endian 32-bit ids) and dm_decoded (the text from the ids)."""
    bound_batches(docs.sparkSession)
    path = path or vocabulary()
    at = docs.columns.index("text")
    docs = docs.withColumn("text", F.col("text").cast("string"))
    added = zip(added_names(docs), (F.array(F.lit(0)), F.lit(0).cast("long"), F.lit(0).cast("long"), F.lit("")), strict=True)
    schema = docs.select("*", *[c.alias(name) for name, c in added]).schema
    for f in schema:
        f.nullable = True

    def run(batches):
        m = model(path, scores)
        for b in batches:
            size = pc.fill_null(pc.binary_length(b.column(at)), 0).to_pylist()
            for lo, hi in runs([range(n) for n in size]):
                part = b.slice(lo, hi - lo)
                ids, n = m.encode(part.column(at))
                edge = np.concatenate(([0], np.cumsum(n)))
                own = [ids[a:z] for a, z in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True)]
                crc = [zlib.crc32(x.astype("<u4").tobytes()) for x in own]
                lists = pa.ListArray.from_arrays(pa.array(edge, pa.int32()), pa.array(ids, pa.int32()))
                yield pa.record_batch([*part.columns, lists, pa.array(n, pa.int64()), pa.array(crc, pa.int64()), pa.array([m.decode(x.tolist()) for x in own], pa.string())], schema.names)

    return docs.mapInArrow(run, schema)


def op2_sentencepiece(spark: SparkSession, sf_dir: str, path: str | None = None) -> DataFrame:
    """(doc_id, n_tokens, ids_crc32, decoded_sha256, round_trip) for every document."""
    docs = table(spark, sf_dir, "documents").select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    done = encode_stage(docs, path)
    return done.select("doc_id", F.col("dm_n_tokens").alias("n_tokens"), F.col("dm_ids_crc32").alias("ids_crc32"), F.sha2(F.col("dm_decoded").cast("binary"), 256).alias("decoded_sha256"), (F.col("dm_decoded") == F.col("text")).alias("round_trip"))
