"""Operations for building language-model training data.

Nothing outside this subpackage imports it; the rest of the library works
without it.
"""
