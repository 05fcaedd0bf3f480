"""A SentencePiece BPE vocabulary read from its model file: pieces, ranks, byte fallback. No training, no encoding."""

from __future__ import annotations

from functools import lru_cache

SPACE_MARK = "▁"


class PieceModel:
    """Pieces with their order of merging. Equal scores share a rank; the leftmost pair then goes first."""

    def __init__(self, path: str):
        import sentencepiece

        m = sentencepiece.SentencePieceProcessor(model_file=path)
        self.path, self.size = path, m.get_piece_size()
        self.pieces = [m.id_to_piece(i) for i in range(self.size)]
        self.byte_ids = [m.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
        self.unknown = m.unk_id()
        self.ids = {p: i for i, p in enumerate(self.pieces) if not (m.is_control(i) or m.is_unknown(i) or m.is_byte(i) or m.is_unused(i))}
        if not all(m.is_byte(i) for i in self.byte_ids):
            raise ValueError("the model has no byte fallback")
        if any(b == SPACE_MARK and a != SPACE_MARK for p in self.ids for a, b in zip(p, p[1:], strict=False)):
            raise ValueError("a piece has white space after other text: words can't be cut apart")
        if not set("".join(self.ids)) <= self.ids.keys():
            raise ValueError("a character of a piece is no piece itself")
        if any("\n" in p for p in self.ids):
            raise ValueError("a piece holds a newline: lines can't be cut apart")
        if m.encode("  a b ", out_type=str) != m.encode("▁ a▁b ", out_type=str) or m.encode("ﬁ", out_type=str) != [SPACE_MARK, "ﬁ"]:
            raise ValueError("the model's normaliser is not the identity with a leading mark")
        ranks = {s: r for r, s in enumerate(sorted({m.get_score(i) for i in self.ids.values()}, reverse=True))}
        self.rank = {p: ranks[m.get_score(i)] for p, i in self.ids.items()}


@lru_cache(maxsize=4)
def load(path: str) -> PieceModel:
    return PieceModel(path)


def normalised(text: str) -> str:
    """The text as the model sees it: white space marked, one mark in front of a text that isn't empty."""
    return SPACE_MARK + text.replace(" ", SPACE_MARK) if text else ""
