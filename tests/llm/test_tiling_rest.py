import numpy as np

from canopy.llm import tiling
from tests.llm.test_tiling import plain_tiles


def test_the_free_rest_of_a_skipped_match_is_searched_again():
    """The excerpt i0..i6 overlaps the tile i5..i11, but i0..i4 is free: 12 of 16, not 7."""
    item, doc = list(range(16)), [*range(5, 12), 99, *range(0, 7), 98, *range(0, 7)]
    tiles = tiling.tile(np.array(doc, np.uint64), np.array(item, np.uint64), 5)
    assert sum(n for _, _, n in tiles) == plain_tiles(doc, item, 5) == 12
