"""Select-join queries as values: predicates, edges, queries; normal forms; compilation to Spark and to SQL."""

from cardest.query.compile import to_column, to_dataframe, to_sql
from cardest.query.ir import And, Clause, JoinEdge, Not, Opaque, Or, Query, between, in_list
from cardest.query.normalize import QueryClass, canonical, classify, clause_count, expand_equalities, to_nnf

__all__ = ["And", "Clause", "JoinEdge", "Not", "Opaque", "Or", "Query", "QueryClass", "between", "canonical", "classify", "clause_count", "expand_equalities", "in_list", "to_column", "to_dataframe", "to_nnf", "to_sql"]
