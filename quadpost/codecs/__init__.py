"""Integer codecs: four-lane ones and the classic ones they are compared with."""


def load() -> None:
    """Registers every codec."""
    from quadpost.codecs import bitwise, bytewise, frames, quad_length, quad_selector, words  # noqa: F401
