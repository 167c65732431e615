"""Inputs that every operator must handle."""


def odd_rows():
    """Nulls, empty and very long texts, ties, repeated rows, odd characters."""
    long = " ".join(f"word{i % 977}x" for i in range(60_000))
    return [
        (1, None, "en", "a"),
        (2, "", None, None),
        (3, "   \t\n", "de", "b"),
        (4, "The quick brown fox, the lazy dog.", "en", "a"),
        (4, "The quick brown fox, the lazy dog.", "en", "a"),
        (5, "The quick brown fox, the lazy dog.", "en", "é"),
        (None, "no id here at all", "fr", "a"),
        (7, long, "en", None),
        (8, "ÀÉ ß 中文 🙂 \x1c\x85 x", "fr", "b"),
        (9, "12 34 !!", "de", "a"),
        (9, "another text under one id", "de", "a"),
    ]
