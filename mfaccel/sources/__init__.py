"""Rating tables from relational, text and JSON sources, and what prepares them."""
