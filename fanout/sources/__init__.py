"""Tables and contact streams, and storage that all executors share."""
