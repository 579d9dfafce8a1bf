"""Multi-way natural joins whose observable behaviour depends on the query and on declared sizes only."""
