"""Models from a key to a bucket or to its share of the sorted order.

Every model is frozen in literals before it meets the data, so a repeated task
gives the same buckets, and never decreases, so buckets come out in key order.
"""

from modelsort.functions.models.base import Composite, Model, WithHeavy
from modelsort.functions.models.ecdf import EcdfBucket, SampleEcdf
from modelsort.functions.models.linear import LinearBucket
from modelsort.functions.models.radix import RadixBucket
from modelsort.functions.models.rmi import Rmi, tune_rmi
from modelsort.functions.models.tree import SplitterTree

__all__ = ["Composite", "EcdfBucket", "LinearBucket", "Model", "RadixBucket", "Rmi", "SampleEcdf", "SplitterTree", "WithHeavy", "tune_rmi"]
