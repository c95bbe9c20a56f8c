"""Training-data operators (documents, pages, labels). Nothing else in the library imports this subpackage."""
