"""The worked problems on the given tables: graphs, queries, reference SQL."""
