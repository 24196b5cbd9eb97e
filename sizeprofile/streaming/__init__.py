"""Group sizes over event streams. The same functions take a batch or a stream."""
