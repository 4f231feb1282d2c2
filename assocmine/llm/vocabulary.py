"""Places of public tokenizer files; the files stay where the installation keeps them."""

from __future__ import annotations


def public_path(name: str) -> str:
    """Path of an installed public vocabulary file, the same on every machine of the cluster."""
    import public_tokenizers

    return public_tokenizers.path(name)
