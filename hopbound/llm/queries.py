"""The registered queries of this subpackage and their SQL."""

from . import chat, media, mixing, packing, pii, quality, simhash, spotsigs, toxicity, urls

QUERIES = {
    "op1_source_mixing": mixing.op1_source_mixing,
    "op2_best_fit_packing": packing.op2_best_fit_packing,
    "op3_media_chunking": media.op3_media_chunking,
    "op4_url_filter": urls.op4_url_filter,
    "op5_spotsigs": spotsigs.op5_spotsigs,
    "op6_pii_sanitisation": pii.op6_pii_sanitisation,
    "op7_simhash_dedup": simhash.op7_simhash_dedup,
    "op8_toxicity": toxicity.op8_toxicity,
    "op9_chat_formatting": chat.op9_chat_formatting,
    "op10_quality_classifier": quality.op10_quality_classifier,
}

ORACLES = {
    "op4_url_filter": urls.ORACLE,
    "op9_chat_formatting": chat.ORACLE,
}
