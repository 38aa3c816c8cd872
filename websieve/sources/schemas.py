"""Schemas of the tables and files, never inferred."""

from __future__ import annotations

PAGE = "page_id bigint, url string, html string"
PAGE_JSON = f"{PAGE}, _corrupt string"
DOCUMENT = "doc_id bigint, text string, lang string, source string, n_chars bigint"
EXTRACT = "url string, digest string, date string, text string"
MANIFEST = "page_id bigint, url string, page_digest string, para_nos array<int>, lang string, lang_score double, ppl double, bucket string"
TELEMETRY = "stage string, docs bigint, cpu_s double, wall_s double"
EVENT = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
