"""BPE encoding and decoding with forced-boundary splitting.

A byte pair that occurs inside no token of the vocabulary can't lie inside a token of any text, so the place between
the two bytes is a certain cut: what stands on either side is encoded on its own and the ids are joined. Cuts are made
twice. First in the text: between a byte of a word and a blank after it (no token holds such a pair, which is tested
when the vocabulary is loaded, and the pre-tokeniser starts a piece there whatever follows). Then in each fragment's
pre-tokens, at each pair that the vocabulary lacks. Fragments repeat a lot, so their ids are kept in a bounded memo.

Defined cases: null text counts as empty and has no ids; repeated rows each get a row; special tokens written out in a
text become their ids, as in the tokenizers library; other columns are ignored; a null id stays null.
"""

from __future__ import annotations

import array
import hashlib
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Memo, slices, tokenizer_path

FRAGMENT = re.compile(r"\s*\S+|\s+")


class ByteBpe:
    """Encoder and decoder of a byte-level BPE file of the tokenizers library."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer
        from tokenizers.pre_tokenizers import ByteLevel

        self.tok = Tokenizer.from_file(path)
        self.tok.no_truncation()
        self.tok.no_padding()
        self.model, self.pre = self.tok.model, self.tok.pre_tokenizer
        added = self.tok.get_added_tokens_decoder()
        self.special = re.compile("|".join(re.escape(t.content) for t in added.values())) if added else None
        size = self.tok.get_vocab_size(with_added_tokens=True)
        tokens = [self.tok.id_to_token(i) or "" for i in range(size)]
        #: Of the mapped characters, which stand for bytes one to one.
        letters = {self._mapped(bytes([b])): b for b in range(128)} | self._high()
        self.bytes = [t.encode() if any(c not in letters for c in t) else bytes(letters[c] for c in t) for t in tokens]
        plain = [t for i, t in enumerate(tokens) if i not in added]
        self.pairs = {t[i : i + 2] for t in plain for i in range(len(t) - 1)}
        if any(re.search(r"\S\s", self.bytes[i].decode("utf-8", "replace")) for i in range(size) if i not in added):
            raise ValueError("this vocabulary has tokens with a blank after a letter or mark: no certain cut in texts")
        assert len(ByteLevel.alphabet()) == len(letters)
        self.memo, self.parts = Memo(self.fragment, 500_000), Memo(self.tokens, 50_000)

    def _mapped(self, b: bytes) -> str:
        return self.tok.pre_tokenizer.pre_tokenize_str(b.decode())[0][0]

    def _high(self) -> dict[str, int]:
        """Characters of the bytes from 128 on: of two-byte texts the second one, of their first bytes the lead."""
        out = {}
        for code in (*range(0x80, 0x800), 0x800, 0x1000, 0x2000, 0x3000, 0x4000, 0x5000, 0x6000, 0x7000, 0x8000, 0x9000, 0xA000, 0xB000, 0xC000, 0xD000, 0xE000, 0xF000, 0x10000, 0x40000, 0x80000, 0xC0000, 0x100000):
            raw = chr(code).encode()
            for c, b in zip("".join(p for p, _ in self.tok.pre_tokenizer.pre_tokenize_str(chr(code))), raw, strict=True):
                out[c] = b
        from tokenizers.pre_tokenizers import ByteLevel

        rest = set(ByteLevel.alphabet()) - set(out) - {self._mapped(bytes([b])) for b in range(128)}
        # bytes that no text holds (0xC0, 0xC1, 0xF5 to 0xFF): in order of their characters
        missing = [b for b in range(128, 256) if b not in out.values()]
        return out | dict(zip(sorted(rest), missing, strict=True))

    def tokens(self, bit: str) -> list[int]:
        return [t.id for t in self.model.tokenize(bit)]

    def part(self, piece: str) -> list[int]:
        """Ids of a pre-token (mapped characters): cut wherever the vocabulary lacks the pair."""
        pairs = self.pairs
        cuts = [i for i in range(1, len(piece)) if piece[i - 1 : i + 1] not in pairs]
        if not cuts:
            return self.parts[piece]
        return [t for a, b in zip([0, *cuts], [*cuts, len(piece)], strict=True) for t in self.parts[piece[a:b]]]

    def fragment(self, text: str) -> bytes:
        """Ids of a fragment as little-endian unsigned 32-bit integers."""
        if self.special and self.special.search(text):
            ids = self.tok.encode(text, add_special_tokens=False).ids
        else:
            ids = [i for p, _ in self.pre.pre_tokenize_str(text) for i in self.part(p)]
        return array.array("I", ids).tobytes()

    def encode(self, text: str) -> bytes:
        return b"".join(map(self.memo.__getitem__, FRAGMENT.findall(text)))

    def decode(self, ids: bytes) -> str:
        table = self.bytes
        return b"".join([table[i] for i in array.array("I", ids)]).decode("utf-8", "replace")


_OPEN: dict[str, ByteBpe] = {}


def byte_bpe(path: str) -> ByteBpe:
    """This process's coder: it serves all tasks that a worker runs."""
    return _OPEN.get(path) or _OPEN.setdefault(path, ByteBpe(path))


def encode_decode(docs: DataFrame, file: str = "byte_bpe_50k.json", id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 (and ids binary, decoded string if asked): one row a row of docs."""
    kind = dict(docs.dtypes)[id_col]

    def run(batches):
        bpe = byte_bpe(tokenizer_path(file))
        for b in slices(batches):
            ids = [bpe.encode(t or "") for t in b.column(1).to_pylist()]
            back = [bpe.decode(i) for i in ids]
            cols = [b.column(0), pa.array([len(i) // 4 for i in ids], pa.int64()), pa.array([hashlib.sha256(i).hexdigest() for i in ids]), pa.array([hashlib.sha256(t.encode()).hexdigest() for t in back])]
            cols += [pa.array(ids, pa.binary()), pa.array(back, pa.string())] if with_ids else []
            yield pa.RecordBatch.from_arrays(cols, ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", *["ids", "decoded"] * with_ids])

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids binary, decoded string" * with_ids)
