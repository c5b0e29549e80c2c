"""Texts that hold an added token get the ids of an unmodified tokenizer."""

import numpy as np
import pytest
from graphsieve.llm.common import PieceEncoder, tokenizer_path
from tokenizers import Tokenizer


@pytest.mark.parametrize(("name", "kind"), [("byte_bpe_50k.json", "byte"), ("word_bpe_49k.json", "word")])
def test_added_tokens(name, kind):
    t, e = Tokenizer.from_file(tokenizer_path(name)), PieceEncoder.get(tokenizer_path(name), kind)
    for text in ["<|endoftext|>", "one two<|endoftext|>three", "a <|endoftext|> B <|startoftext|>  c\n", "<|ENDOFTEXT|> x", "no marker here"]:
        assert e.encode(text) == np.array(t.encode(text, add_special_tokens=False).ids, "<u4").tobytes(), text
