"""The shape of a long word."""

from tricount.llm import quality


def test_shape_reads_the_whole_word():
    one, two = quality._codes("ab" * 100 + "-12"), quality._codes("ab" * 100 + "=AB")
    assert one & 0xFFFFFFFF != two & 0xFFFFFFFF
