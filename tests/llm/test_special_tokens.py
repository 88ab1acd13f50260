"""Token ids equal those of the plain tokenizer, special strings included."""

from corrutil.llm.tokens import WordIds, tokenizer_path

TEXTS = [
    "<|endoftext|>", "<|startoftext|>", "<|ENDOFTEXT|>", "a<|endoftext|>b", "word <|startoftext|> Other\nword<|endoftext|><|endoftext|>", "<|endoftext", "x <|endoftext|",
    "", " ", "don't <|endoftext|>'s", "\u00c9t\u00e9 <|endoftext|> 12 34\t<|startoftext|>", "<|<|endoftext|>|>",
]


def test_ids_of_texts_with_special_strings():
    from tokenizers import Tokenizer

    plain, ids = Tokenizer.from_file(tokenizer_path()), WordIds(tokenizer_path())
    for _ in range(2):
        got = ids([t.encode() for t in TEXTS])
        for text, found in zip(TEXTS, got, strict=True):
            want = plain.encode(text, add_special_tokens=False).ids
            assert [int.from_bytes(found[i : i + 4], "little") for i in range(0, len(found), 4)] == want, text
