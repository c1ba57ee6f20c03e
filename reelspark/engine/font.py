"""A 3 x 5 dot font (own drawing): rows of three dots from the top, as text."""

from __future__ import annotations

import functools

import numpy as np

GLYPHS = {
    "a": "010101111101101", "b": "110101110101110", "c": "011100100100011", "d": "110101101101110", "e": "111100110100111", "f": "111100110100100", "g": "011100101101011",
    "h": "101101111101101", "i": "111010010010111", "j": "001001001101010", "k": "101101110101101", "l": "100100100100111", "m": "101111111101101", "n": "110101101101101",
    "o": "010101101101010", "p": "110101110100100", "q": "010101101011001", "r": "110101110101101", "s": "011100010001110", "t": "111010010010010", "u": "101101101101111",
    "v": "101101101101010", "w": "101101111111101", "x": "101101010101101", "y": "101101010010010", "z": "111001010100111", "0": "111101101101111", "1": "010110010010111",
    "2": "110001010100111", "3": "110001010001110", "4": "101101111001001", "5": "111100110001110", "6": "011100111101111", "7": "111001010010010", "8": "111101111101111",
    "9": "111101111001110", ":": "000010000010000", ".": "000000000000010", "/": "001001010100100", "#": "101111101111101", "-": "000000111000000",
}
ADVANCE, HEIGHT, WIDTH = 4, 5, 3


def glyph(ch: str) -> str:
    return GLYPHS.get(ch.lower(), "0" * 15)


@functools.lru_cache(4096)
def text_mask(text: str, x: int, y: int, scale: int, w: int, h: int) -> np.ndarray:
    mask = np.zeros((h, w), bool)
    for k, ch in enumerate(text):
        left = x + k * ADVANCE * scale
        if left >= w:
            break
        dots = glyph(ch)
        for i, dot in enumerate(dots):
            if dot == "1":
                px, py = left + (i % WIDTH) * scale, y + (i // WIDTH) * scale
                mask[max(0, py) : max(0, py + scale), max(0, px) : max(0, px + scale)] = True
    mask.setflags(write=False)
    return mask


def text_extent(text: str, scale: int = 1) -> tuple[int, int]:
    """Width and height; runs for real when a script is replayed."""
    return (max(0, len(text) * ADVANCE - 1) * scale, HEIGHT * scale if text else 0)
