"""Property graphs over tables: mappings, generic graph tables, change sets."""
