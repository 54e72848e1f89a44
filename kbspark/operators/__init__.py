"""Methods: records, profiling, mining, indices, retrieval, serving, curation, measures, finance."""
