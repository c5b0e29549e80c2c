"""What the encoder keeps while pieces are packed."""

import sys

import pyarrow as pa
from graphsieve.llm import packing
from graphsieve.llm.common import PieceEncoder, tokenizer_path


def test_packer_lets_the_encoder_go():
    encoder = PieceEncoder.get(tokenizer_path("word_bpe_49k.json"), "word")
    assert encoder.led.limit <= 300_000
    one = {n: pa.array([5]) for n in ("uid", "doc_id", "piece", "start", "length", "ids_crc32", "to")}
    assert packing._packer(2048, False)(pa.table(one)).num_rows == 1
    assert not any("encoder" in k for k in sys.modules["graphsieve_worker_state"].kept)
