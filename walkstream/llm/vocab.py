"""Public vocabularies, read on the driver and sent to the executors as bounded values."""

from __future__ import annotations

import os
from dataclasses import dataclass

from . import textkernel as tk

#: Where public tokenizer files lie unless a caller says otherwise.
TOKENIZER_DIR = os.environ.get("WALKSTREAM_TOKENIZERS", "/opt/tokenizers")
PIECE_MODEL = "piece_bpe_32k.model"


@dataclass(frozen=True)
class PieceVocab:
    """Pieces as bytes with the word mark as a blank; `byte_ids[b]` is the piece that stands for the single byte b."""

    key: str
    pieces: tuple[bytes, ...]
    scores: tuple[int, ...]
    kinds: tuple[str, ...]  # 'piece', 'byte' or 'control'

    @property
    def byte_ids(self) -> list[int]:
        out = [-1] * 256
        for i, (p, k) in enumerate(zip(self.pieces, self.kinds, strict=True)):
            if k == "byte":
                out[p[0]] = i
        return out


def load_pieces(path: str | None = None) -> PieceVocab:
    """The vocabulary of a SentencePiece model file; at most a few hundred thousand entries, so it is bounded."""
    import sentencepiece

    path = path or f"{TOKENIZER_DIR}/{PIECE_MODEL}"
    model = sentencepiece.SentencePieceProcessor(model_file=path)
    pieces, scores, kinds = [], [], []
    for i in range(model.vocab_size()):
        text = model.id_to_piece(i)
        if model.is_byte(i):
            pieces.append(bytes([int(text[3:5], 16)]))
            kinds.append("byte")
        elif model.is_control(i) or model.is_unknown(i) or model.is_unused(i):
            pieces.append(b"")
            kinds.append("control")
        else:
            pieces.append(text.replace("▁", " ").encode())
            kinds.append("piece")
        scores.append(int(model.get_score(i)))
    return PieceVocab(f"{path}:{len(pieces)}", tuple(pieces), tuple(scores), tuple(kinds))


@tk.keep_last
def piece_trie(vocab: PieceVocab) -> tk.Trie:
    """One trie for all operators of a worker."""
    known = [(p, i) for i, (p, k) in enumerate(zip(vocab.pieces, vocab.kinds, strict=True)) if k == "piece"]
    return tk.Trie([p for p, _ in known], [i for _, i in known])
