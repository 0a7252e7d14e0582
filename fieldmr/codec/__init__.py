"""Error-bounded codecs of dense arrays, in numpy; Spark stages call them on one chunk of blocks at a time."""

from .backend import pack, unpack
from .blockpred import blockpred_decode, blockpred_encode
from .blockxform import blockxform_decode, blockxform_encode
from .interp import interp_decode, interp_encode, interp_plan
from .schedule import eb_schedule

__all__ = [
    "blockpred_decode", "blockpred_encode", "blockxform_decode", "blockxform_encode", "eb_schedule", "interp_decode", "interp_encode", "interp_plan", "pack", "unpack",
]
