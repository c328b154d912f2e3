import numpy as np
import public_tokenizers

from approxset.llm import textkit


def test_ids_are_the_librarys_below_u0250():
    """Every character alone and in words, also the separators U+001C to U+001F, which were dropped."""
    enc = textkit.WordEncoder(public_tokenizers.path("word_bpe_49k.json"))
    texts = [chr(i) + x for i in range(1, 0x260) for x in ("", "a", "9", ".", "'s", "\u00c91", "\x7f\x00", " b")] + ["\u0130st", "\u023ab", "a\x1fb\u00e9", "\u00bd3\u00b2", "don't", "C'\u00c9tait"]
    want = [e.ids for e in enc.lib.encode_batch(texts, add_special_tokens=False)]
    assert [np.frombuffer(enc.ids(t), enc.dtype).tolist() for t in texts] == want


def test_common_pieces_need_no_byte_mapping():
    """A word of letters is not split, and no piece goes through the library's pre-tokeniser."""
    enc = textkit.WordEncoder(public_tokenizers.path("word_bpe_49k.json"))
    enc.split_ascii = None
    assert np.frombuffer(enc.ids("Word \u00e9t\u00e9"), enc.dtype).tolist() == enc.lib.encode("Word \u00e9t\u00e9", add_special_tokens=False).ids
