"""Models over streams of rows."""
