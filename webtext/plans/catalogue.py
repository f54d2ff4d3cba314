"""All queries; importing the modules registers them."""

from webtext.plans import corpus, evaluation, extraction, relational, streams  # noqa: F401
from webtext.plans.registry import CATALOGUE

__all__ = ["CATALOGUE"]
