"""Private, size-controlled summaries of sparse counts, as DataFrame plans."""
