"""Operators that prepare text for training language models; nothing else in the package imports them."""
