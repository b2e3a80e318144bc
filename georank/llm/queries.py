"""The queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from . import fixity
from .bpe import op8_bpe
from .fixity import op2_fixity
from .hashing import op6_hashing
from .jaccard import op3_jaccard
from .katz import op7_katz
from .language import op10_language
from .mixing import op9_mixing
from .planes import op1_bit_planes
from .quality import op4_quality
from .suffixes import op5_suffixes

QUERIES = {f.__name__: f for f in (op1_bit_planes, op2_fixity, op3_jaccard, op4_quality, op5_suffixes, op6_hashing, op7_katz, op8_bpe, op9_mixing, op10_language)}
ORACLES: dict[str, str] = {"op2_fixity": fixity.ORACLE}
