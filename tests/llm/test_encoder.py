"""What the encoder of the token store looks up, and what it keeps."""

from __future__ import annotations

from knnvote.llm import tokenstore

TEXTS = ["the cat, the dog.\tthe  cat", "", "  ", " Größe' und größe ", "99 don't 9.", "漢字 the", "a×b ÷ ß. ß"] + [f"the word{chr(97 + i % 26)}{chr(97 + i // 26)}x" for i in range(200)]


def ids_of(enc, texts):
    return [enc.tokenizer.encode(t, add_special_tokens=False).ids for t in texts]


def test_each_distinct_word_of_a_block_is_looked_up_once():
    enc, asked = tokenstore.Encoder(), []

    class Counted(type(enc.words)):
        def __getitem__(self, word):
            asked.append(word)
            return super().__getitem__(word)

    enc.words = Counted(enc.tokenizer, enc.width)
    got = enc.encode(["alpha beta alpha"] * 50)
    assert sorted(asked) == ["alpha", "beta"]
    assert [x.tolist() for x in got] == ids_of(enc, ["alpha beta alpha"]) * 50


def test_words_in_use_outlive_a_full_memory(monkeypatch):
    monkeypatch.setattr(tokenstore, "WORDS_KEPT", 20)
    monkeypatch.setattr(tokenstore, "BLOCK", 30)
    enc = tokenstore.Encoder()
    assert [x.tolist() for x in enc.encode(TEXTS)] == ids_of(enc, TEXTS)
    assert len(enc.words) + len(enc.words.older) <= 20
    assert "the" in enc.words or "the" in enc.words.older
    assert not any("," in w and len(w) > 1 for w in [*enc.words, *enc.words.older])


def test_the_encoder_is_given_up_after_the_texts():
    tokenstore._encoder(tokenstore.VOCABULARY)
    assert not list(tokenstore._once(iter([])))
    assert tokenstore._encoder.cache_info().currsize == 0


def test_a_worker_gives_free_memory_back(monkeypatch):
    class Pool:
        calls = 0

        def release_unused(self):
            self.calls += 1

    pool = Pool()
    monkeypatch.setattr(tokenstore.pa, "default_memory_pool", lambda: pool)
    assert not list(tokenstore._once(iter([])))
    assert pool.calls == 1
