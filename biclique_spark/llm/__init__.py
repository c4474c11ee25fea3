"""Training-data operators on whole tables of documents, vectors and conversations."""
