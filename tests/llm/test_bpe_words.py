import public_tokenizers as P

from lowrank_spark.llm.byte_bpe import ByteBpe, load_ranks


def test_words_of_letters_need_no_pattern():
    """Latin words behind a space are merged without the pattern, with the ids that the pattern gives; other parts still go by it."""
    bpe = ByteBpe(load_ranks(P.path("byte_bpe_50k.tiktoken")), P.PATTERN)
    find, seen = bpe.find, []
    bpe.find = lambda s: seen.append(s) or find(s)
    text = "one zwölfßig élèvent ªº donn't ʔʰ ǅx a1 x̀y ſſ" + " letters" * 20 + " " + "q" * 300
    ids = bpe.encode(text)
    assert seen == ["one", " donn't", " ʔʰ", " a1", " x̀y"]
    assert ids == [i for p in find(text) for i in bpe.merge(p.encode())] and bpe.decode(ids) == text.encode()
    assert bpe.merge(b"") == ()


def test_texts_are_merged_together():
    """What is new in a group of texts is merged in one call, with the ids of each text on its own, also where the memo drops a generation."""
    import tiktoken

    ranks = load_ranks(P.path("byte_bpe_50k.tiktoken"))
    ref = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    bpe = ByteBpe(ranks, P.PATTERN)
    calls, merge_all = [], bpe.merge_all
    bpe.merge_all = lambda pieces: calls.append(len(pieces)) or merge_all(pieces)
    bpe.chunk_memo.limit = bpe.piece_memo.limit = 300
    texts = ["", " ", "thethe zwölfßig", "ababab" * 50, "", "one  two", "a1 b2 thethe zwölfßig", " x", "x ", "\n", "ththererein ononinin"] + ["w%d aaaab" % i for i in range(40)]
    at, ids = bpe.encode_all(texts)
    assert calls == [calls[0]] and calls[0] > 40
    assert [ids[i:j].tolist() for i, j in zip(at[:-1], at[1:])] == [ref.encode_ordinary(t) for t in texts]
    raw_at, raw = bpe.decode_all(ids)
    name_at, names = bpe.names_all(ids)
    for t, i, j in zip(texts, at[:-1], at[1:]):
        assert bytes(raw[raw_at[i] : raw_at[j]]) == t.encode()
        assert bytes(names[name_at[i] + 1 : name_at[j]]).decode() == " ".join(map(str, ref.encode_ordinary(t)))
    assert [x.tolist() for x in bpe.encode_all([])] == [[0], []]
