"""Training-data operators: language, quality, sharding, decontamination, extraction,
segmentation, token counts, repeated passages, media payloads and near copies."""
