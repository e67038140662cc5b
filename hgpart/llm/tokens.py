"""Token ids in binary shards, compressed by a Re-Pair grammar and decoded at random."""

from __future__ import annotations

import json
import os
import re
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import as_bytes, column_stretches, mix64, new_path, small_batches, tidy, worker_cache

MAGIC = b"TKR2"
HEAD = "<4sHHIIIIQ"
END = np.zeros(1, np.uint32)
#: Ids of one shard; a longer document makes a longer shard.
SHARD_IDS = 1 << 19
#: Pieces that a worker remembers.
CACHE_WORDS = 700_000

# fixed values: how byte-level BPE of this family cuts a text into pieces, for texts of Latin-1 characters
LETTER, NUMBER, BLANK = "A-Za-z\xaa\xb5\xba\xc0-\xd6\xd8-\xf6\xf8-\xff", "0-9\xb2\xb3\xb9\xbc-\xbe", "\t-\r \x85\xa0"
PIECES = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d| ?[{LETTER}]+| ?[{NUMBER}]+| ?[^{BLANK}{LETTER}{NUMBER}]+|[{BLANK}]+(?![^{BLANK}])|[{BLANK}]+")


class Encoder:
    """Ids by the tokenizers library. Merges never cross pieces, so each distinct piece of a Latin-1 text is encoded once and remembered.

    Texts are cut into pieces by array operations, and pieces are looked up by a 64-bit hash of their characters (a sum of random odd numbers,
    one a place) and compared with the remembered piece byte by byte; a text with a piece that differs is encoded whole. New ones
    go to the library many at a time, on a line each: a line break is a piece and an id of its own, where the ids are cut apart.
    Texts with an apostrophe, which may start a contraction, are cut by the pattern. Texts of other characters or with a special token's
    string, and tokenizers other than byte-level BPE, are encoded whole.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.added = [t.content for t in self.library.get_added_tokens_decoder().values()]
        config = json.loads(self.library.to_str())
        pre = config.get("pre_tokenizer") or {}
        line = self.library.encode("\n", add_special_tokens=False).ids
        self.line = line[0] if len(line) == 1 else None
        self.by_piece = self.line is not None and config["model"]["type"] == "BPE" and not config.get("normalizer") and pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and pre.get("use_regex", True)
        # 0 blank, 1 letter, 2 number, 3 other
        self.kind = np.array([0 if re.match(f"[{BLANK}]", c) else 1 if re.match(f"[{LETTER}]", c) else 2 if re.match(f"[{NUMBER}]", c) else 3 for c in map(chr, range(256))], np.uint8)
        self.power = mix64(np.arange(1, (1 << 12) + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)
        self._forget()

    def _forget(self) -> None:
        self.hash, self.start, self.size, self.flat = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint32)
        # the pieces themselves: bytes one after another, where each begins and how long it is
        self.text, self.text_start, self.text_size = np.zeros(0, np.uint8), np.zeros(0, np.int64), np.zeros(0, np.int64)
        # in how many calls each was met
        self.used = np.zeros(0, np.int32)

    def _trim(self) -> None:
        """Forget pieces met in one call only, or all but the ones met most if that leaves more than half; the others count half from now on."""
        often = max(1, int(np.partition(self.used, -(CACHE_WORDS // 2))[-(CACHE_WORDS // 2)])) if len(self.used) > CACHE_WORDS // 2 else 1
        keep = self.used > often
        self.flat, self.text = _ragged(self.start[keep], self.size[keep], self.flat), _ragged(self.text_start[keep], self.text_size[keep], self.text)
        self.hash, self.size, self.text_size, self.used = self.hash[keep], self.size[keep], self.text_size[keep], self.used[keep] // 2
        self.start, self.text_start = np.cumsum(self.size) - self.size, np.cumsum(self.text_size) - self.text_size

    def _whole(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, np.uint32) for e in self.library.encode_batch_fast(texts, add_special_tokens=False)]

    def _pieces(self, pieces: list[str], at_once: int = 4000) -> tuple[np.ndarray, np.ndarray]:
        """(ids one after another, how many of each piece)."""
        apart = [i for i, p in enumerate(pieces) if not p.strip() or "\n" in p]
        own = set(apart)
        lines = [i for i in range(len(pieces)) if i not in own]
        size, got = np.zeros(len(pieces), np.int64), []
        for i in range(0, len(lines), at_once):
            part = [pieces[j] for j in lines[i:i + at_once]]
            ids = np.array(self.library.encode_batch_fast(["\n" + "\n".join(part)], add_special_tokens=False)[0].ids, np.uint32)
            cuts = np.flatnonzero(ids == self.line)
            if len(cuts) != len(part):
                raise RuntimeError("pieces were not cut at line breaks")
            size[lines[i:i + at_once]] = np.diff(np.append(cuts, len(ids))) - 1
            got.append(ids[ids != self.line])
        whole = self._whole([pieces[i] for i in apart])
        size[apart] = [len(x) for x in whole]
        flat = np.empty(int(size.sum()), np.uint32)
        start = np.cumsum(size) - size
        if lines:
            joined = np.concatenate(got)
            flat[_spread(start[lines], size[lines])] = joined
        for i, x in zip(apart, whole, strict=True):
            flat[start[i]:start[i] + len(x)] = x
        return flat, size

    def _starts(self, data: np.ndarray, begins: np.ndarray) -> np.ndarray:
        """Where pieces start: at changes of kind, but a space before something else belongs to it, and of several blanks there only the last stands apart."""
        kind = self.kind[data]
        new = np.empty(len(data), bool)
        new[0] = True
        np.not_equal(kind[1:], kind[:-1], out=new[1:])
        first = np.zeros(len(data), bool)
        first[begins] = True
        new |= first
        after = np.flatnonzero(new[1:] & (kind[1:] != 0) & (kind[:-1] == 0) & ~first[1:]) + 1
        new[after - 1] = True
        new[after[data[after - 1] == 32]] = False
        return np.flatnonzero(new)

    def _plain(self, text: str) -> bytes | None:
        try:
            data = text.encode("latin-1")
        except UnicodeEncodeError:
            return None
        return None if any(a in text for a in self.added) else data

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of each text."""
        out: list[np.ndarray | None] = [None] * len(texts)
        latin = [self._plain(t) if self.by_piece else None for t in texts]
        other = [i for i, d in enumerate(latin) if d is None]
        for i, ids in zip(other, self._whole([texts[i] for i in other]), strict=True):
            out[i] = ids
        fast = [i for i, d in enumerate(latin) if d]
        for i, d in enumerate(latin):
            if d == b"":
                out[i] = np.zeros(0, np.uint32)
        if not fast:
            return out
        data = np.frombuffer(b"".join(latin[i] for i in fast), np.uint8)
        length = np.array([len(latin[i]) for i in fast], np.int64)
        begins = np.cumsum(length) - length
        starts = self._starts(data, begins)
        quoted = [n for n, i in enumerate(fast) if b"'" in latin[i]]
        if quoted:
            hit = np.zeros(len(fast), bool)
            hit[quoted] = True
            owner = np.searchsorted(begins, starts, side="right") - 1
            extra = [begins[n] + np.cumsum([0, *(len(p) for p in PIECES.findall(texts[fast[n]])[:-1])]) for n in quoted]
            starts = np.sort(np.concatenate([starts[~hit[owner]], *extra]))
        sizes = np.diff(np.append(starts, len(data)))
        inside = np.arange(len(data)) - np.repeat(starts, sizes)
        value = (data.astype(np.uint64) + np.uint64(1)) * self.power[inside & 4095]
        if sizes.max() > 4096:
            value = value * (mix64((inside >> 12).astype(np.uint64)) | np.uint64(1))
        key = mix64(np.add.reduceat(value, starts) + sizes.astype(np.uint64))
        uniq, first, which = np.unique(key, return_index=True, return_inverse=True)
        if len(self.hash) > CACHE_WORDS:
            self._trim()
        pos = np.searchsorted(self.hash, uniq)
        known = np.zeros(len(uniq), bool)
        inner = pos < len(self.hash)
        known[inner] = self.hash[pos[inner]] == uniq[inner]
        fresh = np.flatnonzero(~known)
        if len(fresh):
            raw = data.tobytes()
            begin, long = starts[first[fresh]], sizes[first[fresh]]
            new = [raw[a:a + n] for a, n in zip(begin.tolist(), long.tolist(), strict=True)]
            ids, size = self._pieces([x.decode("latin-1") for x in new])
            where = pos[fresh]
            self.start = np.insert(self.start, where, len(self.flat) + np.cumsum(size) - size)
            self.size = np.insert(self.size, where, size)
            self.text_start = np.insert(self.text_start, where, len(self.text) + np.cumsum(long) - long)
            self.text_size = np.insert(self.text_size, where, long)
            self.hash = np.insert(self.hash, where, uniq[fresh])
            self.used = np.insert(self.used, where, 0)
            self.flat = np.concatenate([self.flat, ids])
            self.text = np.concatenate([self.text, np.frombuffer(b"".join(new), np.uint8)])
            pos = np.searchsorted(self.hash, uniq)
        self.used[pos] += 1
        at = pos[which]
        same = self.text_size[at] == sizes
        if same.all():
            equal = self.text[np.repeat(self.text_start[at], sizes) + inside] == data
            same = equal.all() if equal.all() else np.logical_and.reduceat(equal, starts)
        if not np.all(same):
            # pieces of one hash: whole texts go to the library, one after another without these pieces
            wrong = set((np.searchsorted(begins, starts[~same], side="right") - 1).tolist())
            for n in wrong:
                out[fast[n]] = self._whole([texts[fast[n]]])[0]
            rest = [n for n in range(len(fast)) if n not in wrong]
            for n, ids in zip(rest, self.encode([texts[fast[n]] for n in rest]), strict=True):
                out[fast[n]] = ids
            return out
        ids = _ragged(self.start[at], self.size[at], self.flat)
        ends = np.cumsum(self.size[at])
        # the last piece of each text
        last = np.append(np.searchsorted(starts, begins[1:]) - 1, len(starts) - 1)
        cuts = ends[last]
        for i, a, b in zip(fast, [0, *cuts[:-1].tolist()], cuts.tolist(), strict=True):
            out[i] = ids[a:b]
        return out


def _spread(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Indices start, start + 1, ... of each stretch."""
    ends = np.cumsum(lengths)
    return np.repeat(starts - (ends - lengths), lengths) + np.arange(int(ends[-1]) if len(ends) else 0)


def _ragged(starts: np.ndarray, lengths: np.ndarray, flat: np.ndarray) -> np.ndarray:
    """Concatenation of flat[start:start + length]."""
    return flat[_spread(starts, lengths)]


def _by_pair(seq: np.ndarray, at: np.ndarray, made: int) -> tuple[np.ndarray, np.ndarray]:
    """(positions ordered by the pair that starts there, where each pair's positions begin)."""
    wide, long = np.uint64(made.bit_length()), np.uint64(len(seq).bit_length())
    pair = (seq[at].astype(np.uint64) << wide) | seq[at + 1]
    if 2 * int(wide) + int(long) <= 64:  # pair and position in one number
        both = np.sort((pair << long) | at.astype(np.uint64))
        at, pair = (both & ((np.uint64(1) << long) - np.uint64(1))).astype(np.int64), both >> long
    else:
        order = np.argsort(pair, kind="stable")
        at, pair = at[order], pair[order]
    return at, np.flatnonzero(np.concatenate([[True], pair[1:] != pair[:-1]]))


def re_pair(ids: np.ndarray, ends: np.ndarray, symbols: int, least: int = 2):
    """Replace adjacent pairs by new symbols until none occurs ``least`` times; pairs never reach over a document's end.

    Each round counts exactly all pairs that may be frequent, in a run of one symbol every second: those with a symbol of the last round and
    those that were frequent before, for other pairs only become rarer. Where occurrences overlap, the more
    frequent pair is replaced, and the other counted anew in the next round; the most frequent pair is replaced everywhere, so
    each round makes a rule. Returns (sequence, sequence end of each document,
    rules as (left, right) rows, number of rules after each round). Rules refer only to symbols of earlier rounds.
    """
    seq = ids.astype(np.uint32)
    ends = ends.astype(np.int64)
    rules, after = [], []
    made = symbols
    # pairs that start here may occur often enough
    maybe = np.ones(len(seq), bool)
    while len(seq) > 1:
        free = maybe[:-1].copy()
        free[ends[(ends > 0) & (ends < len(seq))] - 1] = False  # nothing is paired over an end
        twin = np.flatnonzero((seq[:-1] == seq[1:]) & free)
        if len(twin):
            head = np.maximum.accumulate(np.where(np.concatenate([[True], np.diff(twin) != 1]), np.arange(len(twin)), 0))
            free[twin[(np.arange(len(twin)) - head) % 2 == 1]] = False
        at = np.flatnonzero(free)
        if not len(at):
            break
        at, first = _by_pair(seq, at, made)
        count = np.diff(np.append(first, len(at)))
        often = count >= least
        if not often.any():
            break
        at = at[np.repeat(often, count)]
        count = count[often]
        rank = np.empty(len(count), np.int32)
        rank[np.argsort(count, kind="stable")] = np.arange(1, len(count) + 1)
        which = np.repeat(np.arange(len(count)), count)
        # one place of margin before and after
        weight, take = np.zeros(len(seq) + 1, np.int32), np.zeros(len(seq) + 1, bool)
        weight[at + 1] = rank[which]
        for _ in range(3):
            best = at[(weight[at + 1] > weight[at]) & (weight[at + 1] > weight[np.minimum(at + 2, len(seq))])] + 1
            take[best] = True
            weight[best] = weight[best - 1] = weight[np.minimum(best + 1, len(seq))] = 0
        taken = take[at + 1]
        used = np.bincount(which[taken], minlength=len(count)) >= least
        taken &= used[which]
        maybe = np.zeros(len(seq), bool)
        maybe[at] = True
        # of a run, those that were not counted follow the ones that were
        maybe[twin] |= maybe[np.maximum(twin - 1, 0)]
        at, which = at[taken], which[taken]
        number = np.cumsum(used) - 1
        some = np.zeros(len(number), np.int64)
        some[which] = at
        some = some[used]
        rules.append(np.column_stack([seq[some], seq[some + 1]]))
        seq[at] = (made + number[which]).astype(np.uint32)
        gone = np.zeros(len(seq), bool)
        gone[at + 1] = True
        maybe[at] = True
        before = at[at > 0] - 1
        before = np.where(gone[before], before - 1, before)
        maybe[before[before >= 0]] = True
        ends = ends - np.concatenate([[0], np.cumsum(gone)])[ends]
        seq, maybe = seq[~gone], maybe[~gone]
        made += len(some)
        after.append(made - symbols)
    return seq, ends, np.concatenate(rules) if rules else np.zeros((0, 2), np.uint32), after


def _planes(values: np.ndarray, width: int) -> bytes:
    """The lowest bytes of all values, then the next ones, ...: what is left zero or alike lies together for the file's compression."""
    return values.astype("<u4").reshape(-1, 1).view(np.uint8)[:, :width].T.tobytes()


def pack_shard(doc_ids: list, lengths: np.ndarray, ids: np.ndarray, symbols: int, part_start: int) -> bytes:
    """A shard: head, document ids (JSON), ids of each document, sequence ends, rules, expansion lengths, rounds, sequence. Rules, lengths and sequence are in byte planes."""

    seq, ends, rules, after = re_pair(ids, np.cumsum(lengths), symbols)
    size = np.ones(symbols + len(rules), np.uint32)
    low = 0
    for high in after:
        size[symbols + low:symbols + high] = size[rules[low:high, 0]] + size[rules[low:high, 1]]
        low = high
    width = max(1, (symbols + len(rules) - 1).bit_length() + 7 >> 3)
    names = json.dumps(doc_ids).encode()
    head = struct.pack(HEAD, MAGIC, width, len(after), len(names), len(lengths), len(rules), symbols, part_start)
    return b"".join([head, struct.pack("<Q", len(seq)), names, lengths.astype("<u4").tobytes(), ends.astype("<u8").tobytes(), _planes(rules[:, 0], width), _planes(rules[:, 1], width), _planes(size[symbols:], 4), np.array(after, "<u4").tobytes(), _planes(seq, width)])


class Shard:
    """A packed shard; ``document(k)`` decodes one document, ``all_ids()`` every one."""

    def __init__(self, data: bytes):

        magic, width, rounds, n_names, docs, n_rules, symbols, self.part_start = struct.unpack_from(HEAD, data)
        if magic != MAGIC:
            raise ValueError("not a token shard")
        at = struct.calcsize(HEAD)
        (n_seq,) = struct.unpack_from("<Q", data, at)
        at += 8
        self.doc_ids = json.loads(data[at:at + n_names])
        at += n_names

        def take(kind, n):
            nonlocal at
            out = np.frombuffer(data, kind, n, at)
            at += out.nbytes
            return out

        def planes(n, width):
            out = np.zeros((n, 4), np.uint8)
            out[:, :width] = take(np.uint8, n * width).reshape(width, n).T
            return out.view("<u4").ravel()

        self.lengths, self.ends = take("<u4", docs), take("<u8", docs).astype(np.int64)
        rules = np.column_stack([planes(n_rules, width), planes(n_rules, width)])
        sizes, after = planes(n_rules, 4), take("<u4", rounds)
        self.seq = planes(n_seq, width)
        self.size = np.concatenate([np.ones(symbols, np.int64), sizes])
        # expansions of all symbols one after another
        self.start = np.concatenate([[0], np.cumsum(self.size)[:-1]])
        self.flat = np.empty(int(self.size.sum()), np.uint32)
        self.flat[:symbols] = np.arange(symbols)
        low = 0
        for high in after.tolist():
            both = rules[low:high].ravel()
            first = int(self.start[symbols + low])
            got = _ragged(self.start[both], self.size[both], self.flat)
            self.flat[first:first + len(got)] = got
            low = high

    def expand(self, part: np.ndarray) -> np.ndarray:
        return _ragged(self.start[part], self.size[part], self.flat).astype("<u4")

    def document(self, k: int) -> np.ndarray:
        return self.expand(self.seq[(self.ends[k - 1] if k else 0):self.ends[k]])

    def all_ids(self) -> np.ndarray:
        return self.expand(self.seq)


def _packer(path: str, shard_ids: int):
    def run(batches):
        cache = worker_cache()
        encoder = cache.get(("encoder", path)) or cache.setdefault(("encoder", path), Encoder(path))
        symbols = encoder.library.get_vocab_size()
        part = TaskContext.get().partitionId()
        names, ids, lengths, held, start, number = [], [], [], 0, 0, 0

        def shard():
            flat = np.concatenate(ids)
            blob = pack_shard(names, np.array(lengths, np.int64), flat, symbols, start)
            return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([number], pa.int32()), pa.array([len(names)], pa.int64()), pa.array([held], pa.int64()), pa.array([blob], pa.binary())], ["part", "shard", "n_docs", "n_ids", "data"])

        for batch in batches:
            keys = batch.column(0).to_pylist()
            for at, held_texts in column_stretches(batch.column(1)):
                texts = [b.decode("utf-8", "replace") for b in held_texts]
                for key, one in zip(keys[at:at + len(texts)], encoder.encode(texts), strict=True):
                    names.append(key)
                    ids += (one, END)
                    lengths.append(len(one) + 1)
                    held += lengths[-1]
                    if held >= shard_ids:
                        yield shard()
                        start, number = start + held, number + 1
                        names, ids, lengths, held = [], [], [], 0
        if names:
            yield shard()

    return run


def write_tokens(docs: DataFrame, path: str, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", shard_ids: int = SHARD_IDS) -> None:
    """Encode every whole text, append id 0 to each, and store shards under ``path`` in ascending order of id.

    Documents are dealt by ranges of their id and sorted inside (nulls first, then equal ids by text), so
    (part, shard) orders the shards. A shard is one self-contained byte string; Spark's
    Parquet writer stores them, so only committed tasks leave any. Null texts are empty: just the end id.
    Repeated rows are written as often as they come. ``tokenizer`` must be readable on every executor.
    """
    small_batches(docs.sparkSession)
    rows = docs.select(F.col(id_col).alias("id"), as_bytes(text_col).alias("body"))
    rows = rows.repartitionByRange(F.col("id").asc_nulls_first()).sortWithinPartitions(F.col("id").asc_nulls_first(), "body")
    rows.mapInArrow(tidy(_packer(tokenizer, shard_ids)), "part int, shard int, n_docs long, n_ids long, data binary").write.parquet(path)


def _reader(batches):
    for batch in batches:
        for part, data in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            shard = Shard(data.as_py())
            ids = shard.all_ids().tobytes()
            ends = np.cumsum(shard.lengths.astype(np.int64))
            begins = ends - shard.lengths
            crc = [zlib.crc32(ids[4 * a:4 * b]) for a, b in zip(begins.tolist(), ends.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array([part] * len(crc), pa.int32()), pa.array(shard.doc_ids), pa.array(begins + shard.part_start, pa.int64()), pa.array(shard.lengths.astype(np.int64)), pa.array(crc, pa.int64())], ["part", "id", "at", "n_tokens", "ids_crc32"])


def read_token_index(spark: SparkSession, path: str, id_col: str = "doc_id", id_type: str = "bigint") -> DataFrame:
    """One row per stored document: id, start, n_tokens, ids_crc32, from decoding every shard.

    Starts add up per part; the parts, as many as the writer had tasks, are summed on the driver.
    """
    table = spark.read.parquet(path)
    totals = table.groupBy("part").agg(F.sum("n_ids").alias("n")).collect()
    offsets, at = [], 0
    for r in sorted(totals, key=lambda r: r["part"]):
        offsets.append((r["part"], at))
        at += r["n"]
    offset = spark.createDataFrame(offsets, "part int, before long")

    def typed(batches):
        for b in _reader(batches):
            yield b.set_column(1, "id", b.column(1).cast(wanted)) if b.column(1).type != wanted else b

    wanted = pa.string() if id_type == "string" else pa.int64()
    rows = table.select("part", "data").mapInArrow(tidy(typed), f"part int, id {'string' if id_type == 'string' else 'bigint'}, at long, n_tokens long, ids_crc32 long")
    return rows.join(F.broadcast(offset), "part").select(F.col("id").cast(id_type).alias(id_col), (F.col("before") + F.col("at")).alias("start"), "n_tokens", "ids_crc32")


def token_round_trip(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Write the shards to the shared folder and return what decoding them finds."""
    path = new_path(docs.sparkSession, "tokens")
    write_tokens(docs, path, tokenizer, id_col, text_col)
    return read_token_index(docs.sparkSession, path, id_col, docs.schema[id_col].dataType.simpleString())
