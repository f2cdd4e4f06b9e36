"""All queries of the engine and their SQL."""

from . import catalog_data, catalog_grid, catalog_more, catalog_stream

QUERIES = {**catalog_grid.QUERIES, **catalog_data.QUERIES, **catalog_stream.QUERIES, **catalog_more.QUERIES}
SQL = {**catalog_grid.SQL, **catalog_data.SQL, **catalog_stream.SQL, **catalog_more.SQL}
