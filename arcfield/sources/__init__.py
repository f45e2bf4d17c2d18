"""Sky views, stores and the region-text data source."""
