"""The fixed public piece vocabulary, read from its model file."""

from __future__ import annotations

from functools import lru_cache

from . import common as C


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


@lru_cache(2)
def model_bytes(path: str) -> bytes:
    fs, p = C.local_path(path)
    with fs.open_input_stream(p, compression=None) as f:
        return f.read()


@lru_cache(2)
def vocabulary(path: str) -> tuple[list[str], list[float], list[int]]:
    """Pieces, scores and types (1 normal, 2 unknown, 3 control, 6 byte) by id."""
    import sentencepiece as spm
    from sentencepiece import sentencepiece_model_pb2 as pb

    m = pb.ModelProto()
    m.ParseFromString(model_bytes(path))
    return [p.piece for p in m.pieces], [p.score for p in m.pieces], [p.type for p in m.pieces]
