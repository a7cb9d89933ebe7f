"""Ids by public engines, whichever pattern cuts a text."""

import random

from sqltutor.llm.queries import tokenizer
from sqltutor.llm.tokens import Library


def test_both_patterns_give_the_librarys_ids():
    coder, rng = Library(tokenizer()), random.Random(5)
    parts = [*"ab'sé9.,$ \n\t\r\u180e\xa0\x1c字", " don't", " foo", "\n\n", " 12", "'ll "]
    texts = ["".join(rng.choices(parts, k=rng.randrange(12))) for _ in range(5000)]
    want = [x.ids for x in coder.library.encode_batch(texts, add_special_tokens=False)]
    assert [coder.ids(t) for t in texts] == want


def test_texts_without_touching_white_space_take_the_pattern_that_never_looks_ahead(monkeypatch):
    coder = Library(tokenizer())
    want = {t: coder.library.encode(t, add_special_tokens=False).ids for t in ("one two\nthree é", "one  two", "a\n\nb", "a\tb", "")}
    monkeypatch.setattr(coder, "engine", None)
    assert coder.ids("one two\nthree é") == want["one two\nthree é"] and coder.ids("") == []
    monkeypatch.undo()
    monkeypatch.setattr(coder, "plain", None)
    assert all(coder.ids(t) == want[t] for t in ("one  two", "a\n\nb", "a\tb"))
