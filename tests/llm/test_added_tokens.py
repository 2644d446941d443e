"""Literals of added tokens get the ids of the unmodified library."""

from __future__ import annotations

from tokenizers import Tokenizer

from nbflow.llm import slack_packing


def test_ids_of_added_tokens_are_the_librarys():
    path = slack_packing.default_vocabulary()
    encoder, library = slack_packing.ByteBpe(path), Tokenizer.from_file(path)
    assert encoder.added
    for x in encoder.added:
        for text in (x, f"a{x}b", f"the end {x} of it", f"{x}{x} \n", "plain text", x[:-1]):
            assert encoder.ids(text).tolist() == library.encode(text, add_special_tokens=False).ids
