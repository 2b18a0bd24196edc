"""Registered queries by kind."""

from . import checked, extensions, methods, relational, scalars, streams

CATALOGS = (methods.catalog, checked.catalog, relational.catalog, scalars.catalog, extensions.catalog, streams.catalog)
