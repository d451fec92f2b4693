"""New words go to the tokenizers library many at a time, and get the ids that it gives each text."""

import random

import numpy as np
import public_tokenizers

from dyntri.llm import token_files

ODD = ["İs", "\xadx", "東京", "é", "ΟΔΟΣ", "ﬁn", "\x1ca", "<|endoftext|>", "x\xa0y"]


def test_new_words_in_one_call(monkeypatch):
    tok = token_files.WordTokenizer(public_tokenizers.path("word_bpe_49k.json"))
    draw = random.Random(3)
    parts = ["'", "'s", "'LL", "'re", "t", "É", "ß", "Ⱥ", "Word", "12", "½", "..", "«", "_", "<"]
    words = list(dict.fromkeys("".join(draw.choices(parts, k=draw.randint(1, 6))) for _ in range(3000)))
    alone, word = [], tok.word
    monkeypatch.setattr(tok, "word", lambda w: alone.append(w) or word(w))
    texts = [*words, *ODD, " ".join(words[:50] + ODD), ""]
    raw = [t.encode() for t in texts]
    ids, counts = tok.ids(np.frombuffer(b"".join(raw), np.uint8), np.cumsum([0, *map(len, raw)]))
    ends = np.cumsum(counts)
    for text, a, b in zip(texts, ends - counts, ends):
        assert ids[a:b].tolist() == tok.tokenizer.encode(text, add_special_tokens=False).ids, text
    assert {w.decode() for w in alone} == set(ODD)
