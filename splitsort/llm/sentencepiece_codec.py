"""SentencePiece encoding and decoding on the tokenizers library.

The model's protobuf is parsed here; normaliser, metaspace marker, piece scores and byte fallback are
rebuilt as a ``tokenizers`` pipeline, for unigram and for BPE models.  If no piece of the vocabulary
has the space marker after another character, no merge and no lattice edge can cross the start of a
run of spaces: a text then falls into chunks that are encoded independently and exactly, and equal
chunks are encoded once.  Parity with the sentencepiece library is verified on a fixed set of probe
texts whenever a model is loaded, and over whole tables in the tests.
"""

from __future__ import annotations

import re
import struct
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import released, small_batches, widened

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
MARK = "▁"
#: Fixed values of the model format: types of pieces, types of models.
NORMAL, UNKNOWN, CONTROL, USER_DEFINED, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
UNIGRAM, BPE = 1, 2
#: Chunks that a worker remembers before it starts afresh, and those it keeps from task to task; the letters and signs that finer cuts may part.
REMEMBERED, KEPT = 80_000, 20_000
LETTER, SIGNS = "[A-Za-zÀ-ɏ]", ".,!?*#$%&|;:()\n"
PROBES = (
    "", " ", "a", "  two  spaces ", "line\nline\ttab", "Ünïcode ñandú çédille", "日本語のテキスト", "emoji 👩‍🚀 zwj",
    "<s> </s> <unk> <0x41>", "▁mark▁ inside", "x" * 300, "1234567890 3.14", " nbsp​", "ﬁ ligature", "aaaa bbbb  cccc   ",
)


def _varint(b: bytes, i: int) -> tuple[int, int]:
    value = shift = 0
    while True:
        byte = b[i]
        i += 1
        value |= (byte & 127) << shift
        shift += 7
        if byte < 128:
            return value, i


def _fields(b: bytes) -> Iterator[tuple[int, int | bytes]]:
    """Field numbers and raw values of one protobuf message."""
    i = 0
    while i < len(b):
        key, i = _varint(b, i)
        wire = key & 7
        if wire == 0:
            value, i = _varint(b, i)
        elif wire == 2:
            n, i = _varint(b, i)
            value, i = b[i : i + n], i + n
        elif wire in (1, 5):
            n = 8 if wire == 1 else 4
            value, i = b[i : i + n], i + n
        else:
            raise ValueError(f"wire type {wire} in a model file")
        yield key >> 3, value


class Codec:
    """A loaded model: ``encode`` and ``decode`` lists, exactly as the sentencepiece library would."""

    def __init__(self, blob: bytes, verify: bool = True) -> None:
        from tokenizers import Regex, Tokenizer, decoders, models, normalizers

        pieces, kind, charsmap, dummy, squeeze, escape, fallback, surface = [], UNIGRAM, b"", True, True, True, False, " \u2047 ".encode()
        for field, value in _fields(blob):
            if field == 1:
                p = dict(_fields(value))
                pieces.append((p[1].decode(), struct.unpack("<f", p.get(2, b"\0\0\0\0"))[0], p.get(3, NORMAL)))
            elif field == 2:
                t = dict(_fields(value))
                kind, fallback, surface = t.get(3, UNIGRAM), bool(t.get(35, 0)), t.get(44, surface)
            elif field == 3:
                n = dict(_fields(value))
                charsmap, dummy, squeeze, escape = n.get(2, b""), bool(n.get(3, 1)), bool(n.get(4, 1)), bool(n.get(5, 1))
        if kind not in (UNIGRAM, BPE) or any(t == USER_DEFINED for *_, t in pieces):
            raise ValueError("only unigram and BPE models without user-defined symbols can be rebuilt")
        unk = next(i for i, (*_, t) in enumerate(pieces) if t == UNKNOWN)
        self.blob, self.dummy = blob, dummy
        if kind == BPE:
            use = {p: i for i, (p, _, t) in enumerate(pieces) if t == NORMAL}
            merges = []
            for p, i in use.items():
                merges += [(-pieces[i][1], i, k) for k in range(1, len(p)) if p[:k] in use and p[k:] in use]
            merges = [(pieces[i][0][:k], pieces[i][0][k:]) for _, i, k in sorted(merges)]
            model = models.BPE(
                vocab={p: i for i, (p, *_) in enumerate(pieces)}, merges=merges, unk_token=pieces[unk][0], fuse_unk=True, byte_fallback=fallback, cache_capacity=0
            )
        else:
            low = min(s for _, s, t in pieces if t == NORMAL) - 100.0
            model = models.Unigram([(p, s if t in (NORMAL, BYTE) else low) for p, s, t in pieces], unk_id=unk, byte_fallback=fallback)
        mark = MARK if escape else " "
        steps = [normalizers.Precompiled(charsmap)] if charsmap else []
        if squeeze:
            steps += [normalizers.Replace(Regex(" {2,}"), " "), normalizers.Replace(Regex(r"\A | \z"), "")]
        self.clean = normalizers.Sequence(steps) if steps else None
        self.escape = escape
        self.tok = Tokenizer(model)
        self.tok.decoder = decoders.Sequence([decoders.Replace(mark, " "), decoders.ByteFallback(), decoders.Fuse()])
        plain = [p for p, _, t in pieces if t == NORMAL]
        inside = re.compile(f"[^{MARK}]{MARK}")
        self.chunk = None
        if escape and not any(inside.search(p) for p in plain):
            self.chunk = re.compile(f"{MARK}*[^{MARK}]*")
            # Finer cuts, where unknown characters can't fuse: between a letter and a sign that no piece joins.
            pairs = {p[k : k + 2] for p in plain for k in range(len(p) - 1)}
            signs = [c for c in SIGNS if not any(q[1] == c and re.match(LETTER, q[0]) for q in pairs)]
            if fallback and signs and not any("\n" in p for p in plain):
                signs = re.escape("".join(signs))
                self.chunk = re.compile(f"{MARK}*{LETTER}+(?=[{signs}])|{MARK}*[^{MARK}\n]+|\n|{MARK}+")
        # A unigram lattice would take a control or byte piece that a text spells out; such texts go to the other library.
        self.literal = re.compile("|".join(re.escape(p) for p, _, t in pieces if t != NORMAL)) if kind == UNIGRAM else None
        self.unk, self.surface, self.squeeze = unk, surface.decode(), squeeze
        self.lead = {i: p == MARK for i, (p, _, t) in enumerate(pieces) if t == NORMAL and p.startswith(MARK)}
        self.starts = bytearray(t == NORMAL and p.startswith(MARK) for p, _, t in pieces)
        self.skip = {i for i, (*_, t) in enumerate(pieces) if t == CONTROL}
        # What the library decodes each id to by itself; ids from here that depend on their neighbours are odd.
        self.alone = self.tok.decode_batch([[i] for i in range(len(pieces))], skip_special_tokens=False)
        high = {i for i, (p, _, t) in enumerate(pieces) if t == BYTE and int(p[1:-1], 16) >= 128}
        self.odd = self.skip | high | {i for i, (*_, t) in enumerate(pieces) if t == UNKNOWN}
        self.encoded: dict[str, list[int]] = {}
        self.decoded: dict[tuple[int, ...], str] = {}
        if verify:
            self.verify(list(PROBES))

    def _marked(self, text: str) -> str:
        if self.clean is not None:
            text = self.clean.normalize_str(text)
        if not text:
            return ""
        text = " " + text if self.dummy else text
        return text.replace(" ", MARK) if self.escape else text

    def encode(self, texts: list[str]) -> list[list[int]]:
        """Ids of whole texts; chunks that are not known yet go to the library in one multithreaded batch."""
        if self.literal is not None and (spelt := [k for k, t in enumerate(texts) if self.literal.search(t)]):
            import sentencepiece

            ref, some = sentencepiece.SentencePieceProcessor(model_proto=self.blob), set(spelt)
            own = iter(self.encode([t for k, t in enumerate(texts) if k not in some]))
            return [ref.encode(t) if k in some else next(own) for k, t in enumerate(texts)]
        marked = [self._marked(t) for t in texts]
        if self.chunk is None:
            return [e.ids for e in self.tok.encode_batch_fast(marked, add_special_tokens=False)]
        if len(self.encoded) > REMEMBERED:
            self.encoded.clear()
        known, cut = self.encoded, self.chunk.findall
        known[""] = []
        split = [cut(m) for m in marked]
        new = list(set().union(*split).difference(known))
        for c, e in zip(new, self.tok.encode_batch_fast(new, add_special_tokens=False), strict=True):
            known[c] = e.ids
        out = []
        for chunks in split:
            out.append(list(chain.from_iterable(map(known.__getitem__, chunks))))
        return out

    def decode(self, lists: list[list[int]]) -> list[str]:
        """Texts of id lists.  Ids that decode alike everywhere are joined; otherwise ids are cut before pieces that
        start with the marker, where no byte run is cut."""
        starts, known = self.starts, self.decoded
        if len(known) > REMEMBERED:
            known.clear()
        split, new = [], {}
        for ids in lists:
            if self.odd.isdisjoint(ids):
                split.append("".join(map(self.alone.__getitem__, ids)))
                continue
            if self.skip and not self.skip.isdisjoint(ids):
                ids = [i for i in ids if i not in self.skip]
            if self.unk in ids:  # runs between unknowns are decoded by themselves
                at = [-1, *[k for k, i in enumerate(ids) if i == self.unk], len(ids)]
                runs = [ids[a + 1 : b] for a, b in zip(at, at[1:], strict=False)]
                split.append(self.surface.join(self.tok.decode_batch(runs, skip_special_tokens=False)))
                continue
            cuts = [k for k, i in enumerate(ids) if starts[i]]
            if not cuts or cuts[0]:
                cuts.insert(0, 0)
            parts = [tuple(ids[a:b]) for a, b in zip(cuts, [*cuts[1:], len(ids)], strict=True)]
            for p in parts:
                if p not in known:
                    new[p] = None
            split.append(parts)
        fresh = list(new)
        for p, t in zip(fresh, self.tok.decode_batch([list(p) for p in fresh], skip_special_tokens=False), strict=True):
            known[p] = t
        out = []
        for ids, parts in zip(lists, split, strict=True):
            text = parts if isinstance(parts, str) else "".join([known[p] for p in parts])
            out.append(text[self._leading(ids) :])
        return out

    def _leading(self, ids: list[int]) -> int:
        """Spaces that markers at the start stand for and the text hasn't: one, or one for each lone marker where spaces are squeezed."""
        n = 0
        for i in ids if self.dummy or self.squeeze else ():
            if i in self.skip:
                continue
            if i not in self.lead:
                break
            n += 1
            if not self.lead[i] or not self.squeeze:
                break
        return n

    def forget(self) -> None:
        """Drop chunks remembered beyond what a first slice finds anyway; the worker may do other work next."""
        for known in (self.encoded, self.decoded):
            if len(known) > KEPT:
                known.clear()

    def verify(self, texts: list[str]) -> None:
        """Raise unless ids and texts equal those of the sentencepiece library."""
        import sentencepiece

        ref = sentencepiece.SentencePieceProcessor(model_proto=self.blob)
        want = ref.encode(texts)
        if (got := self.encode(texts)) != want:
            bad = next(t for t, a, b in zip(texts, got, want, strict=True) if a != b)
            raise ValueError(f"ids differ from the sentencepiece library's: {bad[:80]!r}")
        back = [ref.decode(ids) for ids in want]
        if (text := self.decode(want)) != back:
            bad = next(b for a, b in zip(text, back, strict=True) if a != b)
            raise ValueError(f"decoded text differs from the sentencepiece library's: {bad[:80]!r}")


@lru_cache(2)
def codec(blob: bytes) -> Codec:
    """One codec for each worker process and model."""
    return Codec(blob)


def _texts(column: pa.Array, most: int = 1 << 20) -> Iterator[tuple[int, list[str]]]:
    """Texts of a column in slices of bounded size, each with its number of rows."""
    part, size = [], 0
    for t in column:
        t = t.as_py() or ""
        part.append(t)
        size += len(t)
        if size >= most:
            yield len(part), part
            part, size = [], 0
    if part:
        yield len(part), part


def encode_decode(docs: DataFrame, text: str = "text", model: str = MODEL) -> DataFrame:
    """All rows and columns of ``docs`` with ``ids``, ``n_tokens`` and ``decoded``.

    Whole texts, null as empty (no ids, decoded to the empty text).  ``decoded`` is what the ids alone
    give back.  The model file (under 8 MB) is read on the driver, through Spark, and shipped with the
    function.  Columns called like the three new ones are replaced.  No shuffle.
    """
    docs = docs.drop("ids", "n_tokens", "decoded")
    small_batches(docs.sparkSession)
    blob = model_bytes(docs, model)
    at, names = docs.columns.index(text), docs.columns
    schema = widened(docs, ids="array<int>", n_tokens="long", decoded="string")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(blob)
        for batch in batches:
            done = 0
            for n, texts in _texts(batch.column(at)):
                ids = own.encode(texts)
                new = [pa.array(ids, pa.list_(pa.int32())), pa.array([len(i) for i in ids], pa.int64()), pa.array(own.decode(ids), pa.string())]
                yield pa.RecordBatch.from_arrays([*batch.slice(done, n).columns, *new], [*names, "ids", "n_tokens", "decoded"])
                done += n
        own.forget()

    return docs.mapInArrow(lambda b: released(run(b)), schema)


def model_bytes(df: DataFrame, path: str) -> bytes:
    """The model: a local file of the driver, or any path that Spark reads."""
    try:
        with open(path, "rb") as f:
            return f.read()
    except OSError:
        return bytes(df.sparkSession.read.format("binaryFile").load(path).select(F.col("content")).first()[0])
