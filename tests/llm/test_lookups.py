"""Known texts cost one lookup."""

from graphsieve.llm.common import PieceEncoder, Recent, tokenizer_path


def test_known_texts_are_looked_up_once(monkeypatch):
    e = PieceEncoder(tokenizer_path("byte_bpe_50k.json"), "byte")
    first = e.encode("some words, of a text")
    monkeypatch.setattr(Recent, "missing", lambda *a: 1 / 0)
    assert e.encode("some words, of a text") == first
