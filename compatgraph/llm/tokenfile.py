"""Token-ID files: flat little-endian unsigned integers, one file a partition, and 64-bit document offsets.

Writing takes two jobs.  The first orders documents by range partitions of doc_id, encodes them and
writes each partition's ids as one flat file with the token counts of its documents.  The prefix sums
of the partitions' totals (a few numbers a partition) give their bases; the second job adds them to
write each partition's 64-bit offsets.  Reading maps the files into memory.

Ids are stored in 16 bits where the tokenizer's vocabulary allows it, else in 32.  Each attempt of a task writes
its own file and renames it when complete, so a lost executor leaves no half file.  An offset file holds the doc_ids (signed 64-bit), one
byte a document that says if its doc_id is null, and the offsets (unsigned 64-bit, one more than documents).

Null texts count as empty: such a document has the end id only.  Rows of equal doc_id are ordered by text hash, null doc_ids
come first.  An empty table gives files of no document; a very long text is encoded alone; other columns, whatever their names, are not read.
"""

from __future__ import annotations

import json
import math
import uuid
import zlib
from array import array

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Recent, col, known_bytes, narrow, shared_dir, slices

#: Pieces in a generation of a worker's cache.
CACHE_PIECES = 500_000
#: Code points of the longest word that is cached.
LONGEST = 100
#: Bytes of text that one token file is made for.
FILE_BYTES = 128 << 20
#: Marks a word at the start of a line: a code point that is no character.
FIRST = "\uffff"
#: Marks that may end a word; an apostrophe is none of them, as it can begin a contraction.
MARKS = ".,;:!?#*$%&|"
_WORKERS: dict[str, "Encoder"] = {}


class Encoder:
    """The tokenizers library with a cache of words.

    The vocabulary's split pattern starts a new piece at each single space or line end that stands between
    characters other than white space, so what stands between two of these is encoded by the library on its own, once for
    each distinct string.  Texts with other white space next to a space or line end, or with the string of a special
    token, go through the library whole.  That holds for a byte-level split pattern without a normaliser or a space put in front; with any
    other tokenizer all texts go through the library whole.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            text = f.read()
        self.lib, form = Tokenizer.from_str(text), json.loads(text)
        split = form.get("pre_tokenizer") or {}
        self.by_words = form.get("normalizer") is None and form["model"].get("type") == "BPE" and split.get("type") == "ByteLevel" and split.get("use_regex", True) and not split.get("add_prefix_space", True)
        self.lib.no_truncation()
        self.special = [t.content for t in self.lib.get_added_tokens_decoder().values()]
        vocab = self.lib.get_vocab()
        self.size = max(vocab.values()) + 1
        self.spaced = np.zeros(self.size, bool)
        if self.by_words:
            space = self.lib.encode(" ").tokens[0]
            self.spaced[[i for t, i in vocab.items() if t[:1] == space]] = True
        self.cache = Recent(CACHE_PIECES)

    def whole(self, text: str) -> bytes:
        return array("I", self.lib.encode(text, add_special_tokens=False).ids).tobytes()

    def word(self, w: str) -> bytes | None:
        """Ids of a word: with the space before it, or none after FIRST; None if it can't stand alone."""
        if w == "\n":
            return self.whole(w)
        text = w.removeprefix(FIRST)
        if not text or text[0].isspace() or text[-1].isspace():
            return None
        core = text.rstrip(MARKS)
        if core != text and core[-1:].isalpha():
            return self.known(w[: len(core) - len(text)]) + self.known(FIRST + text[len(core) :])  # marks after a letter are a piece of their own
        return self.whole(text if w[0] == FIRST else " " + text)

    def letters(self, words: list[str]) -> None:
        """Encode words of letters only, each one piece with its space, many in a call: ids are cut at the tokens that begin with a space."""
        parts = [words[i : i + 256] for i in range(0, len(words), 256)]
        for own, e in zip(parts, self.lib.encode_batch_fast([" " + " ".join(p) for p in parts], add_special_tokens=False), strict=True):
            ids = np.array(e.ids, "<u4")
            cuts, raw = [*np.flatnonzero(self.spaced[ids]).tolist(), len(ids)], ids.tobytes()
            if len(cuts) == len(own) + 1:
                self.cache.young.update(zip(own, [raw[4 * a : 4 * b] for a, b in zip(cuts, cuts[1:], strict=False)], strict=True))

    def known(self, w: str) -> bytes | None:
        young = self.cache.young
        if w in young:
            return young[w]
        ids = self.cache.old[w] if w in self.cache.old else self.word(w)
        if len(w) <= LONGEST:
            young[w] = ids
        return ids

    def __call__(self, batch: pa.Array) -> list[bytes]:
        """Ids of each text, as little-endian 32-bit integers.

        Arrow splits the texts, numbers their words and gathers the ids of the words; Python sees each distinct word once.
        """
        batch = pc.fill_null(batch.cast(pa.large_string()), "")
        if not self.by_words:
            return [self.whole(t) for t in batch.to_pylist()]
        apart = pc.match_substring(batch, FIRST)
        for s in self.special:
            apart = pc.or_(apart, pc.match_substring(batch, s))
        lines = pc.replace_substring(pc.if_else(apart, "", batch), "\n", " \n " + FIRST)
        words = pc.split_pattern(pc.binary_join_element_wise(*[pa.scalar(x, pa.large_string()) if isinstance(x, str) else x for x in (FIRST, lines, "")]), " ")
        numbered = words.values.dictionary_encode()
        names = numbered.dictionary.to_numpy(zero_copy_only=False).tolist()
        new = self.cache.missing({w for w in names if len(w) <= LONGEST})
        cores = {w.rstrip(MARKS) for w in new}
        self.letters([w for w in cores if w.isalpha() and w not in self.cache.young and w not in self.cache.old])
        for w in new:
            self.known(w)
        young = self.cache.young
        ids = pa.array([young[w] if w in young else self.known(w) for w in names], pa.large_binary()).take(numbered.indices)
        first = words.offsets.to_numpy()
        whole = set(np.flatnonzero(apart.to_numpy(zero_copy_only=False)).tolist())
        if ids.null_count:
            alone = np.flatnonzero(ids.is_null().to_numpy(zero_copy_only=False))
            whole.update((np.searchsorted(first, alone, "right") - 1).tolist())
        at, raw = np.frombuffer(ids.buffers()[1], "<i8")[first].tolist(), memoryview(ids.buffers()[2])
        return [self.whole(batch[i].as_py()) if i in whole else raw[a:b] for i, (a, b) in enumerate(zip(at, at[1:], strict=False))]


def encoder(path: str) -> Encoder:
    if path not in _WORKERS:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        _WORKERS[path] = Encoder(path)
    return _WORKERS[path]


def write(docs: DataFrame, tokenizer: str, *, end_id: int = 0, out: str | None = None) -> str:
    """Write the token files of ``docs`` and return their folder."""
    spark = docs.sparkSession
    out = out or f"{shared_dir(spark)}/tokens-{uuid.uuid4().hex}"
    size = max(encoder(tokenizer).size, end_id + 1)
    if end_id < 0 or size > 1 << 32:
        raise ValueError("ids must fit unsigned 32-bit integers")
    width = 2 if size <= 1 << 16 else 4
    pafs.FileSystem.from_uri(out)[0].create_dir(pafs.FileSystem.from_uri(out)[1], recursive=True)

    end = np.array([end_id], "<u4").tobytes()

    def run(batches):
        fs, base = pafs.FileSystem.from_uri(out)
        task = TaskContext.get()
        name = f"part-{task.partitionId():06d}"
        temp, ids, none, sizes = f"{base}/.{name}-{task.taskAttemptId()}", [], [], []
        with fs.open_output_stream(temp) as f:
            for batch in batches:
                for part in slices(batch, "text"):
                    coded = encoder(tokenizer)(col(part, "text"))
                    sizes += [len(x) // 4 + 1 for x in coded]
                    f.write(np.frombuffer(end.join([*coded, b""]), "<u4").astype(f"<u{width}").tobytes())
                    keys = col(part, "doc_id")
                    ids.append(keys.fill_null(0).to_numpy()), none.append(keys.is_null().to_numpy(zero_copy_only=False))
        if not sizes:
            fs.delete_file(temp)
            return
        with fs.open_output_stream(temp + ".len") as f:
            f.write(np.array([np.concatenate(ids), np.concatenate(none), np.array(sizes)], "<i8").tobytes())
        fs.move(temp, f"{base}/{name}.bin")
        fs.move(temp + ".len", f"{base}/{name}.len")
        yield pa.RecordBatch.from_pydict({"part": [name], "n_docs": [len(sizes)], "n_tokens": [int(sum(sizes))]})

    keyed = narrow(docs, "doc_id", "text").withColumn("h", F.xxhash64("text"))
    # the size that Catalyst knows from the files: no pass over them
    n = max(int(spark.conf.get("spark.sql.shuffle.partitions")), math.ceil(known_bytes(keyed) / FILE_BYTES) if docs.inputFiles() else 1)
    ranged = keyed.repartitionByRange(n, "doc_id", "h").sortWithinPartitions("doc_id", "h").drop("h")
    # one row a partition: its bases are their prefix sums
    parts = sorted(ranged.mapInArrow(run, "part string, n_docs long, n_tokens long").collect())
    first = np.cumsum([0, *[p.n_tokens for p in parts]])
    rows = [(p.part, p.n_docs, p.n_tokens, int(b), width) for p, b in zip(parts, first[:-1], strict=True)]

    def offsets(batches):
        fs, base = pafs.FileSystem.from_uri(out)
        for batch in batches:
            for name, start in zip(batch.column(0).to_pylist(), batch.column(3).to_pylist(), strict=True):
                with fs.open_input_file(f"{base}/{name}.len") as f:
                    ids, none, sizes = np.frombuffer(f.read(), "<i8").reshape(3, -1)
                temp = f"{base}/.{name}-{TaskContext.get().taskAttemptId()}.idx"
                with fs.open_output_stream(temp) as f:
                    f.write(ids.astype("<i8").tobytes() + none.astype("u1").tobytes() + (start + np.cumsum([0, *sizes])).astype("<u8").tobytes())
                fs.move(temp, f"{base}/{name}.idx")
            yield batch

    manifest = spark.createDataFrame(rows, MANIFEST).repartition(max(1, min(n, len(rows))))
    done = manifest.mapInArrow(offsets, MANIFEST)
    done.write.json(f"{out}/manifest")
    return out


MANIFEST = "part string, n_docs long, n_tokens long, base long, width int"


def read(spark, out: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document of the files."""

    def run(batches):
        fs, base = pafs.FileSystem.from_uri(out)
        for batch in batches:
            for name, n, width in zip(*(batch.column(i).to_pylist() for i in (0, 1, 4)), strict=True):
                with fs.open_input_file(f"{base}/{name}.idx") as f:
                    raw = f.read()
                ids, none, at = np.frombuffer(raw[: 8 * n], "<i8"), np.frombuffer(raw[8 * n : 9 * n], bool), np.frombuffer(raw[9 * n :], "<u8").astype(np.int64)
                if isinstance(fs, pafs.LocalFileSystem):
                    tokens = np.memmap(f"{base}/{name}.bin", f"<u{width}", "r")
                else:
                    with fs.open_input_file(f"{base}/{name}.bin") as f:
                        tokens = np.frombuffer(f.read(), f"<u{width}")
                for i in range(0, n, 10_000):
                    own = at[i : i + 10_001]
                    crc = [zlib.crc32(tokens[a:b].astype("<u4").tobytes()) for a, b in zip(own[:-1] - at[0], own[1:] - at[0], strict=True)]
                    yield pa.RecordBatch.from_arrays([pa.array(ids[i : i + 10_000], mask=none[i : i + 10_000]), pa.array(own[:-1]), pa.array(np.diff(own)), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    parts = spark.read.schema(MANIFEST).json(f"{out}/manifest")
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    return parts.repartition(n).mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")
