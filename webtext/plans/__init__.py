"""Named queries over the given tables, each with the SQL that checks it where SQL can."""

from webtext.plans.catalogue import CATALOGUE

__all__ = ["CATALOGUE"]
