"""Named queries over the tables and their SQL counterparts."""

from . import class_queries, graph_queries, network_queries, process_queries, relational, stream_queries, workload_queries

MODULES = (graph_queries, class_queries, process_queries, network_queries, stream_queries, workload_queries, relational)
