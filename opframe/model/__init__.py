"""Types, paths and operations of the data model."""
