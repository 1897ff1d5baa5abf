"""Tables in, tables out: scratch folders, the star view, and the archive as a data source."""
