import numpy as np

from edgeloc.llm import media


def feature(n, at, bin_of_256):
    """Of silence with a loud tone in 64 samples."""
    x = np.full(n, 128.0)
    x[at : at + 64] += 100 * np.sin(2 * np.pi * bin_of_256 * np.arange(64) / 256)
    times, marks = media.landmarks(x.round().astype(np.uint8).tobytes())
    return times.tolist(), marks.tolist()


def test_tail_and_frame_borders_are_in_the_feature():
    for n, at in ((320, 256), (448, 384), (1088, 1024), (64, 0), (1024, 0), (1024, 224)):
        assert feature(n, at, 20) != feature(n, at, 60), (n, at)
