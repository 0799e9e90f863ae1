"""SentencePiece encoding and decoding through the tokenizers library.

The model file is parsed as a protobuf message; from it come the normaliser, the metaspace marker, the pieces with
their scores (a unigram model), or the merges that the scores of a BPE model imply, and the byte fallback. The
driver reads the file once and broadcasts its bytes (a model has a fixed size); no executor needs the file.

Where no piece holds the marker behind another character, no piece crosses the beginning of a word, so words
can be encoded apart: a task encodes the words it hasn't met in one batch (which the library spreads over threads)
and remembers them, up to a bound. A BPE model's new words go through both libraries behind each other in texts of `JOINED`, and
are told apart by the pieces that begin with the marker. Other models are encoded text by text, in batches.

The round trip and parity with the sentencepiece library are checked for every text. Where words can be encoded apart, that library, too, joins no
pieces across words, so each word is compared when a task meets it and a text agrees if all its words do; other texts are compared whole.

Defined results: a null or empty text has no pieces and decodes to itself; a text that holds the marker character or
lone surrogates doesn't come back as it was, which `round_trip` tells; a column with the name of the output is replaced.
"""

from __future__ import annotations

import hashlib
import itertools
import os
import zlib
from array import array

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hamcover.llm.batchwise import with_struct

#: A model file that the driver can read; a parameter of read_model().
MODEL = "/opt/tokenizers/piece_bpe_32k.model"
MARK = "▁"
#: Words whose pieces a task remembers before it forgets all of them.
REMEMBERED = 200_000
#: New words that are encoded as one text.
JOINED = 200
#: Threads of a task that the tokenizers library may use.
THREADS = "2"
#: One text in so many, by a checksum of its bytes, is compared with the sentencepiece library. 1: every text; 0: none.
PARITY_EVERY = 1

#: Piece types and model types of the file format: fixed values.
NORMAL, UNKNOWN, CONTROL, USER, BYTE = 1, 2, 3, 4, 6
UNIGRAM, BPE = 1, 2


class Backend:
    def __init__(self, model: bytes):
        from sentencepiece import sentencepiece_model_pb2
        from tokenizers import AddedToken, Regex, Tokenizer, decoders, models, normalizers, pre_tokenizers

        proto = sentencepiece_model_pb2.ModelProto()
        proto.ParseFromString(model)
        pieces = [(p.piece, p.score, p.type) for p in proto.pieces]
        kind, norm = proto.trainer_spec.model_type, proto.normalizer_spec
        unk = next((i for i, p in enumerate(pieces) if p[2] == UNKNOWN), 0)
        self.ids = {p: i for i, (p, _, _) in enumerate(pieces)}
        self.kinds = [t for _, _, t in pieces]
        if kind == UNIGRAM:
            self.model = models.Unigram([(p, s) for p, s, _ in pieces], unk, proto.trainer_spec.byte_fallback)
        elif kind == BPE:
            self.model = models.BPE(vocab=self.ids, merges=self._merges(pieces), unk_token=pieces[unk][0], byte_fallback=proto.trainer_spec.byte_fallback, fuse_unk=True)
        else:
            raise ValueError("only unigram and BPE models")
        steps = [normalizers.Precompiled(norm.precompiled_charsmap)] if norm.precompiled_charsmap else []
        if norm.remove_extra_whitespaces:
            steps += [normalizers.Strip(), normalizers.Replace(Regex(" {2,}"), " ")]
        if norm.add_dummy_prefix:
            steps.append(normalizers.Prepend(MARK if norm.escape_whitespaces else " "))
        if norm.escape_whitespaces:
            steps.append(normalizers.Replace(" ", MARK))
        user = [p for p, _, t in pieces if t == USER]
        crossing = any(MARK in p.lstrip(MARK) for p in self.ids)
        self.tokenizer = Tokenizer(self.model)
        self.tokenizer.normalizer = normalizers.Sequence(steps)
        if not crossing:
            self.tokenizer.pre_tokenizer = pre_tokenizers.Split(Regex(f"{MARK}+[^{MARK}]*"), "isolated")
        if user:
            self.tokenizer.add_tokens([AddedToken(p, normalized=True) for p in user])
        decode = [decoders.Replace(MARK, " "), decoders.ByteFallback(), decoders.Fuse()]
        if norm.add_dummy_prefix:
            decode.append(decoders.Strip(" ", 1, 0))
        self.tokenizer.decoder = decoders.Sequence(decode)
        self.by_word = not crossing and not user and not steps[:-2] and norm.add_dummy_prefix and norm.escape_whitespaces
        self.piece_bytes = None
        if self.by_word and pieces[unk][2] == UNKNOWN and proto.trainer_spec.byte_fallback:
            raw = [bytes([int(p[3:5], 16)]) if t == BYTE else p.replace(MARK, " ").encode() for p, _, t in pieces]
            sizes = np.array([len(x) for x in raw], np.int32)
            self.piece_bytes = np.frombuffer(b"".join(raw), np.uint8), (np.cumsum(sizes) - sizes).astype(np.int32), sizes
        self.joins = self.by_word and kind == BPE
        self.opens = np.array([p.startswith(MARK) for p, _, _ in pieces])
        self.bytes, self.other = model, None
        self.known: dict[str, bytes] = {}
        #: Those of the known words that the sentencepiece library encodes otherwise.
        self.differ: set[str] = set()

    def compare(self) -> None:
        """From now on words are compared with the sentencepiece library when they are met."""
        if self.other is None:
            from sentencepiece import SentencePieceProcessor

            self.other = SentencePieceProcessor(model_proto=self.bytes)
            self.known.clear()

    def forget(self) -> None:
        self.known, self.differ = {}, set()

    def _same(self, texts: list[str], packed: list[bytes]) -> list[bool]:
        return [_packed(x) == y for x, y in zip(self.other.encode(texts, num_threads=1), packed, strict=True)] if texts else []

    def parity(self, texts: list[str], packed: list[bytes]) -> list[bool]:
        """Whether the sentencepiece library encodes each text alike; for texts that encode() had last, after compare()."""
        if not self.by_word:
            return self._same(texts, packed)
        whole = [self._as_one(t) for t in texts]
        rest = iter(self._same(list(itertools.compress(texts, whole)), list(itertools.compress(packed, whole))))
        return [next(rest) if as_one else not self.differ or self.differ.isdisjoint(t.split(" ")) for t, as_one in zip(texts, whole, strict=True)]

    @staticmethod
    def _as_one(t: str) -> bool:
        """A run of markers belongs to the word behind it, so such texts go to the tokenizer whole."""
        return bool(t) and (t[0] == " " or t[-1] == " " or "  " in t or MARK in t)

    @staticmethod
    def _merges(pieces: list[tuple[str, float, int]]) -> list[tuple[str, str]]:
        """All ways to make a piece of two others, best score first. Ties by the parts' ids."""
        ids = {p: i for i, (p, _, _) in enumerate(pieces)}
        found = []
        for p, score, kind in pieces:
            if kind == NORMAL:
                found += [(-score, ids[p[:k]], ids[p[k:]]) for k in range(1, len(p)) if p[:k] in ids and p[k:] in ids]
        return [(pieces[a][0], pieces[b][0]) for _, a, b in sorted(found)]

    def encode(self, texts: list[str]) -> list[bytes]:
        """Piece ids of each text, as 32-bit integers. Words are what a space begins; the empty word is a marker alone."""
        if not self.by_word:
            return [_packed(e.ids) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]
        whole = [self._as_one(t) for t in texts]
        split = [[] if as_one or not t else t.split(" ") for t, as_one in zip(texts, whole, strict=True)]
        if len(self.known) > REMEMBERED:
            self.known.clear()
            self.differ.clear()
        self._learn(list({w for words in split for w in words if w not in self.known}))
        rest = iter(self.tokenizer.encode_batch_fast(list(itertools.compress(texts, whole)), add_special_tokens=False))
        get = self.known.__getitem__
        return [_packed(next(rest).ids) if as_one else b"".join(map(get, words)) for words, as_one in zip(split, whole, strict=True)]

    def _learn(self, new: list[str]) -> None:
        """Words without spaces or markers; both libraries encode each, if they are compared."""
        alone = new
        if self.joins:
            groups = [new[i : i + JOINED] for i in range(0, len(new), JOINED)]
            texts = list(map(" ".join, groups))
            other = self.other.encode(texts, num_threads=1) if self.other else itertools.repeat(None)
            alone = []
            for words, e, theirs in zip(groups, self.tokenizer.encode_batch_fast(texts, add_special_tokens=False), other, strict=False):
                ids = np.array(e.ids, np.int32)
                cuts = np.flatnonzero(self.opens[ids])
                if len(cuts) != len(words) or (theirs is not None and theirs != e.ids):
                    alone += words  # the words have to be told apart, or those that differ
                    continue
                data, cuts = ids.tobytes(), [*(4 * cuts).tolist(), 4 * len(ids)]
                self.known.update(zip(words, [data[a:b] for a, b in itertools.pairwise(cuts)], strict=True))
        for w, e in zip(alone, self.tokenizer.encode_batch_fast(alone, add_special_tokens=False), strict=True):
            self.known[w] = _packed(e.ids)
        if self.other:
            self.differ.update(w for w, same in zip(alone, self._same(alone, [self.known[w] for w in alone]), strict=True) if not same)

    def decode(self, flat: np.ndarray, offsets: np.ndarray) -> list[str]:
        """Texts of piece ids: those of one text are flat[offsets[k]:offsets[k + 1]].

        Each piece is some bytes (a byte piece just one), so texts are their bytes behind each other. Models whose pieces aren't
        so plain go through the library's decoder."""
        if self.piece_bytes is None:
            rows = [flat[a:b].tolist() for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
            return self.tokenizer.decode_batch(rows, skip_special_tokens=False)
        data, starts, sizes = self.piece_bytes
        size = sizes[flat]
        ends = np.cumsum(size)
        at = np.repeat(starts[flat] - (ends - size), size)
        at += np.arange(len(at), dtype=at.dtype)
        out = data[at].tobytes()
        cuts = np.concatenate([[0], ends])[offsets].tolist()
        return [out[a + 1 : b].decode("utf-8", "replace") for a, b in zip(cuts[:-1], cuts[1:], strict=True)]


def _packed(ids: list[int]) -> bytes:
    return array("i", ids).tobytes()


#: Backends of this process by the checksum of their model: a worker that runs several tasks builds them once.
_BACKENDS: dict[str, Backend] = {}


def backend_of(model: bytes) -> Backend:
    key = hashlib.sha256(model).hexdigest()
    if key not in _BACKENDS:
        _BACKENDS.clear()
        _BACKENDS[key] = Backend(model)
    return _BACKENDS[key]


def read_model(path: str = MODEL) -> bytes:
    with open(path, "rb") as f:
        return f.read()


def encode_pieces(docs: DataFrame, model: bytes, text: str = "text", output: str = "pieces", parity_every: int = PARITY_EVERY) -> DataFrame:
    """All columns of docs and a struct: ids, round_trip, parity (null for texts that aren't compared)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        os.environ.setdefault("RAYON_NUM_THREADS", THREADS)  # before the library starts its threads
        backend = backend_of(shared.value)
        if parity_every:
            backend.compare()

        def work(texts: list[str | None]) -> tuple[pa.Array, ...]:
            texts = [t or "" for t in texts]
            packed = backend.encode(texts)
            sizes = np.fromiter(map(len, packed), np.int64, len(packed)) // 4
            flat = np.frombuffer(b"".join(packed), np.int32)
            offsets = np.concatenate([[0], np.cumsum(sizes)])
            back = [a == b for a, b in zip(backend.decode(flat, offsets), texts, strict=True)]
            same: list[bool | None] = [None] * len(texts)
            if parity_every:
                picked = [k for k, t in enumerate(texts) if parity_every == 1 or zlib.crc32(t.encode("utf-8", "surrogatepass")) % parity_every == 0]
                for k, x in zip(picked, backend.parity([texts[k] for k in picked], [packed[k] for k in picked]), strict=True):
                    same[k] = x
            return pa.ListArray.from_arrays(offsets.astype(np.int32), flat), pa.array(back), pa.array(same, pa.bool_())

        work.done = backend.forget
        return work

    return with_struct(docs, text, output, "struct<ids:array<int>,round_trip:boolean,parity:boolean>", make)


def decode_pieces(rows: DataFrame, model: bytes, ids: str = "ids", output: str = "decoded") -> DataFrame:
    """All columns and a struct with the text of each array of piece ids; null for null."""
    shared = rows.sparkSession.sparkContext.broadcast(model)

    def make():
        backend = backend_of(shared.value)

        def work(values: list[list[int] | None]) -> list[tuple]:
            rows = [v or [] for v in values]
            offsets = np.concatenate([[0], np.cumsum([len(v) for v in rows])]).astype(np.int64)
            flat = np.fromiter(itertools.chain.from_iterable(rows), np.int32, int(offsets[-1]))
            return [(None if v is None else t,) for v, t in zip(values, backend.decode(flat, offsets), strict=True)]

        return work

    return with_struct(rows, ids, output, "struct<text:string>", make)


def op9_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    found = encode_pieces(docs, read_model())
    ids = F.col("pieces.ids")
    return found.select(
        "doc_id",
        F.size(ids).cast("long").alias("n_pieces"),
        F.sha2(F.array_join(ids, ","), 256).alias("ids_sha256"),
        F.col("pieces.round_trip").alias("round_trip"),
        F.col("pieces.parity").alias("parity"),
    )


QUERIES = {"op9_pieces": op9_pieces}
ORACLES: dict[str, str] = {}
