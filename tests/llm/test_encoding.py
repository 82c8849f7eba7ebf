"""A bounded cache of words gives the tokenizer's ids."""

import pytest


@pytest.mark.parametrize("name, lead", [("word_bpe_49k.json", ""), ("byte_bpe_50k.json", " ")])
def test_small_cache_gives_the_same_ids(name, lead):
    import public_tokenizers
    from tokenizers import Tokenizer

    from approxboot.llm.encoding import WordEncoder

    path = public_tokenizers.path(name)
    enc, plain = WordEncoder(path, lead, max_words=50), Tokenizer.from_file(path)
    for i in range(40):
        texts = [f"the common words and rare{j}x{i} again the words" for j in range(30)]
        ids, lengths = enc.encode(texts)
        want = [e.ids for e in plain.encode_batch(texts, add_special_tokens=False)]
        assert ids.tolist() == [x for e in want for x in e] and lengths.tolist() == [len(e) for e in want]
        assert len(enc.words) <= 50 and len(enc.starts) == len(enc.lengths) == len(enc.met) == len(enc.words)
    assert "common" in {w.strip() for w in enc.words}
