"""Codecs between a bitmap's words and bytes: NAME.encode(words, n_rows) and NAME.decode(payload, n_rows).

NAME.nonzero_size(numbers, values, n_rows) is the length in bytes of the payload of sparse words.
"""

from . import bytealigned, deflate, flag31, marker32, marker64, plain, poslist, runlength

CODECS = {m.__name__.rpartition(".")[2]: m for m in (marker32, marker64, flag31, runlength, bytealigned, deflate, plain, poslist)}
