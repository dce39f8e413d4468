from regionfilter.llm import bpe, packing


def test_packing_alone_learns_no_chunk_twice():
    """Its encoder holds more chunks than the pipeline's, which share memory with other stages."""
    enc = bpe.encoder(packing.TOKENIZER, packing.ALONE)
    assert enc is bpe.encoder(packing.TOKENIZER, packing.ALONE) and enc is not bpe.encoder()
    text = [" ".join(f"w{i}" for i in range(at, at + 20_000)) for at in range(0, 240_000, 20_000)]
    first = [enc.encode_many([t])[0] for t in text]
    learned, learn = [], enc._learn
    enc._learn = lambda chunks: (learned.extend(chunks), learn(chunks))
    assert [enc.encode_many([t])[0] for t in text] == first and not learned
    assert first[0] == bpe.encoder().encode_many(text[:1])[0]
    del enc._learn
